"""Mixing sources to target weights by systematic sampling.

Each document's expected copies are summed up along its source, one random offset is added, and the document is taken
once for each whole number that its stretch of the sum crosses.  All documents of a source have the same expected
copies, so the sum before a document is its place times that.  Within a source the walk goes from long to short
documents, to and fro within each stretch that adds up to one, so the words taken stay near the target.

No source is gathered in one task: documents fall into (source, size class, hash) buckets, the buckets' totals are
summed up on a small table, and only the rows of one bucket are sorted together.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import clean_columns, stage
from .words import GAP

#: Rows that one bucket holds on average at most.
BUCKET_ROWS = 256


def _md5_number(*parts: Column) -> Column:
    """A number of 52 bits from the md5 of the parts (null: as the word null)."""
    text = F.concat_ws("|", *(F.coalesce(p.cast("string"), F.lit("null")) for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def word_count(text: Column) -> Column:
    """Number of words of a text, 0 for null."""
    parts = F.split(F.coalesce(text, F.lit("")), GAP)
    empty_ends = (parts[0] == "").cast("long") + ((F.size(parts) > 1) & (F.element_at(parts, -1) == "")).cast("long")
    return F.size(parts).cast("long") - empty_ends


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = 3) -> DataFrame:
    """One row per source with ``target``: shares of all words by weight, none above ``most`` times its own words.

    ``sizes`` has (source, source_size, source_rows).  Sources by code point, null last, get the weights in turn.  The
    share of capped sources goes to the others by weight: with sources sorted by the level at which each is full, the
    common level is the first that the next source's cap exceeds.  Sums are exact integers.  A table of sources is one
    row per source, sorted by Spark with spilling.
    """
    by_name = Window.orderBy(F.col("source").isNull(), F.col("source").cast("binary"))
    turn = F.pmod(F.row_number().over(by_name) - 1, F.lit(len(weights)))
    weight = F.element_at(F.array(*(F.lit(int(w)) for w in weights)), (turn + 1).cast("int")).cast("long")
    ranked = sizes.withColumn("weight", weight).withColumn("full_at", F.lit(float(most)) * F.col("source_size") / F.col("weight"))
    order = (F.col("full_at"), F.col("source").isNull(), F.col("source").cast("binary"))
    before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rest = Window.orderBy(*order).rowsBetween(0, Window.unboundedFollowing)
    everything = Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    level = (F.sum("source_size").over(everything) - most * F.coalesce(F.sum("source_size").over(before), F.lit(0))) / F.sum("weight").over(rest)
    leveled = ranked.withColumn("level", level)
    common = F.max(F.when(F.col("level") <= F.col("full_at"), F.col("level"))).over(everything)
    target = F.least(F.lit(float(most)) * F.col("source_size"), common * F.col("weight"))
    return leveled.select("source", "source_size", "source_rows", F.coalesce(target, F.lit(float(most)) * F.col("source_size")).alias("target"))


def mix_sources(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = 3, seed: str = "mix", text: str = "text") -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken for each row of ``docs``.

    A null or empty text has size 0, is walked last in its source and takes 0 words whatever its copies.  Repeated
    rows are sampled separately.  A null source is a source of its own.  An empty table gives an empty result.  Other
    columns of ``docs`` are ignored.  Equal input gives equal output whatever its partitions.
    """
    rows = clean_columns(docs, "doc_id", "source", text).select("doc_id", "source", word_count(F.col(text)).alias("size"), F.coalesce(F.sha2(F.col(text), 256), F.lit("")).alias("tie"))
    rows = stage(rows, "mix-sizes")
    return systematic(rows, weights, most, seed)


def systematic(rows: DataFrame, weights: tuple[int, ...], most: int, seed: str) -> DataFrame:
    """The sampling itself, over rows (doc_id, source, size, tie, ...)."""
    sizes = stage(rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("source_rows")), "mix-sources")
    targets = stage(source_targets(sizes, weights, most), "mix-targets")
    n_rows = targets.agg(F.sum("source_rows")).first()[0] or 0
    spread = max(1, -(-n_rows // (BUCKET_ROWS * 8)))
    size_class = F.length(F.bin(F.col("size") + 1))
    # a null source is a key of its own; plain equality lets the join below use the windows' partitioning
    key = {"source_": F.coalesce("source", F.lit("")), "none_": F.col("source").isNull()}
    placed = rows.withColumns({**key, "class_": size_class, "part_": F.pmod(_md5_number(F.lit(seed), F.col("doc_id"), F.col("tie")), F.lit(spread)).cast("int")})
    totals = placed.groupBy("source_", "none_", "class_", "part_").agg(F.count("*").alias("n"))
    # rows before a bucket: the classes of a source from long to short, then its parts
    per_class = totals.groupBy("source_", "none_", "class_").agg(F.sum("n").alias("class_n"))
    class_start = F.sum("class_n").over(Window.partitionBy("source_", "none_").orderBy(F.desc("class_"))) - F.col("class_n")
    part_start = F.sum("n").over(Window.partitionBy("source_", "none_", "class_").orderBy("part_")) - F.col("n")
    starts = totals.withColumn("part_start", part_start).join(per_class.withColumn("class_start", class_start).drop("class_n"), ["source_", "none_", "class_"])
    draw = (_md5_number(F.lit(seed), F.col("source")) + 0.5) / float(1 << 52)
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    known = targets.withColumns({**key, "offset": draw, "rate": rate}).drop("source")
    known = stage(starts.join(known, ["source_", "none_"]).withColumn("before", F.col("part_start") + F.col("class_start")).drop("n", "part_start", "class_start"), "mix-buckets")
    bucket = ["source_", "none_", "class_", "part_"]
    here = Window.partitionBy(*bucket).orderBy(F.desc("size"), F.col("doc_id").asc_nulls_last(), "tie")
    ranked = placed.withColumn("rank_", F.row_number().over(here))
    joined = ranked.join(known, bucket)
    whole, part = F.floor("rate"), F.col("rate") - F.floor("rate")
    # walk to and fro: each second stretch of 1 / part documents is walked from its short end
    at = F.col("before") + F.col("rank_")
    turn = F.floor((at - 1) * part)
    low, high = F.ceil(F.try_divide(turn, part)) + 1, F.least(F.ceil(F.try_divide(turn + 1, part)), F.col("source_rows"))
    step = F.when((part > 0) & (turn % 2 == 1) & at.between(low, high), low + high - at).otherwise(at)
    copies = (whole + F.floor(step * part + F.col("offset")) - F.floor((step - 1) * part + F.col("offset"))).cast("long")
    extra = [c for c in rows.columns if c not in ("doc_id", "source", "size", "tie")]
    return joined.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"), *extra)


def take_copies(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), most: int = 3, seed: str = "mix") -> DataFrame:
    """The mix itself: the rows of ``docs`` with all their columns (whatever those are called), each as often as it is taken.

    Rows with null or empty texts are taken at their source's rate, a null source is a source of its own, repeated rows are
    sampled separately, and an empty table gives an empty result.
    """
    columns = docs.columns
    carried = {f"in_{i}_": F.col(f"`{c}`") for i, c in enumerate(columns)}
    tie = F.coalesce(F.sha2(F.col("text"), 256), F.lit(""))
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), tie.alias("tie"), *(v.alias(k) for k, v in carried.items()))
    taken = systematic(rows, weights, most, seed).filter("copies > 0")
    taken = taken.withColumn("copy_", F.explode(F.sequence(F.lit(1), F.col("copies").cast("int"))))
    return taken.select(*(F.col(f"in_{i}_").alias(c) for i, c in enumerate(columns)))
