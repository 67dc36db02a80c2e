"""Quality rules at two levels: base rules on each document, then a verdict on its host.

Failures are aggregated by host, each host's failure rate is shrunk towards the rate of all hosts by a beta prior fitted
to the hosts themselves, and the verdict is joined back to the documents.  Only DataFrame functions are used.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import clean_columns, stage
from .words import GAP

#: Base rules.
MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30
WINDOW = 8
#: A host is rejected where its shrunken failure rate is above this.
MAX_HOST_RATE = 0.5
SYMBOLS = "#*$%&|<>"
_SPACES = " \t\n\x0b\x0c\r"


def _measured(rows: DataFrame, text: str) -> DataFrame:
    """``rows`` with the base measures of column ``text`` (null: no words)."""
    t = F.coalesce(F.col(text), F.lit(""))
    squeezed = F.trim(F.regexp_replace(t, GAP, " "))
    lines = F.filter(F.split(t, "\n"), lambda x: F.length(F.translate(x, _SPACES, "")) > 0)
    out = rows.withColumns(
        {
            "words_": F.when(F.length(squeezed) > 0, F.split(squeezed, " ")).otherwise(F.array().cast("array<string>")),
            "word_chars": F.length(F.translate(t, _SPACES, "")).cast("long"),
            "n_symbols": (F.length(t) - F.length(F.translate(t, SYMBOLS, ""))).cast("long"),
            "lines_": lines,
        }
    )
    out = out.withColumn("n_words", F.size("words_").cast("long"))
    out = out.withColumn("n_dup_lines", (F.size("lines_") - F.size(F.array_distinct("lines_"))).cast("long"))
    return out.withColumn("n_repeat_words", _repeat_words()).drop("words_", "lines_")


def _repeat_words() -> Column:
    """Words covered by windows of ``WINDOW`` words that occur twice or more in the text.

    Windows are compared by hash.  Only where a hash repeats at all are the places sorted by hash, neighbours of equal
    hash kept, and the stretches they cover added up in order.
    """
    return _covered(F.transform("words_", lambda w: F.xxhash64(w)))


def _let(value: Column, body) -> Column:
    """``body`` of ``value``, which is computed once for the row."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _covered(hashes: Column) -> Column:
    def windows(h: Column) -> Column:
        n = F.size(h) - WINDOW + 1
        starts = F.when(n > 0, F.sequence(F.lit(0), F.greatest(n - 1, F.lit(0)))).otherwise(F.array().cast("array<int>"))
        return F.transform(starts, lambda i: F.xxhash64(*(F.get(h, i + k) for k in range(WINDOW))))

    def stretch(places: Column) -> Column:
        # each place covers up to the next one, the last one a whole window
        return F.aggregate(
            F.zip_with(places, F.slice(places, 2, F.greatest(F.size(places), F.lit(1))), lambda a, b: F.coalesce(F.least(b - a, F.lit(WINDOW)), F.lit(WINDOW))),
            F.lit(0).cast("long"),
            lambda s, x: s + x,
        )

    def repeated(w: Column) -> Column:
        at = F.array_sort(F.transform(w, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        return _let(
            at,
            lambda s: F.array_sort(
                F.transform(
                    F.filter(s, lambda x, i: (x.h == F.get(s, i - 1).h) | (x.h == F.get(s, i + 1).h)),
                    lambda x: x.i,
                )
            ),
        )

    return _let(
        _let(hashes, windows),
        lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0).cast("long")).otherwise(_let(repeated(w), stretch)),
    )


def base_failed() -> Column:
    return (F.col("n_words") < MIN_WORDS) | (100 * F.col("n_repeat_words") > MAX_REPEAT_PERCENT * F.col("n_words"))


def host_verdicts(rows: DataFrame, host: str = "source", failed: str = "base_failed", max_rate: float = MAX_HOST_RATE) -> DataFrame:
    """One row per host: host, n_docs, n_failed, shrunk_rate, host_rejected.

    The prior is fitted by moments.  With m the mean rate over documents and v the spread of host rates around it
    (weighted by documents) less the part that chance alone makes, its strength is m(1-m)/v - 1, kept within [1, 1e6].
    With one host, or hosts no more different than by chance, the prior is strong and the rate is that of all.
    A null host is a host of its own.
    """
    per = stage(rows.groupBy(F.col(host).alias("host")).agg(F.count("*").alias("n_docs"), F.sum(F.col(failed).cast("long")).alias("n_failed")), "host-counts")
    mean = per.agg((F.sum("n_failed") / F.sum("n_docs")).alias("m"), F.sum("n_docs").alias("n"), F.count("*").alias("k"))
    per1 = per.crossJoin(F.broadcast(mean))
    spread = F.sum(F.col("n_docs") * F.pow(F.col("n_failed") / F.col("n_docs") - F.col("m"), F.lit(2.0)))
    moments = per1.groupBy("m", "n", "k").agg(spread.alias("ss"))
    chance = F.col("m") * (1 - F.col("m")) * F.col("k") / F.col("n")
    v = F.col("ss") / F.col("n") - chance
    strength = F.when(v > 0, F.col("m") * (1 - F.col("m")) / v - 1).otherwise(F.lit(1e6))
    prior = moments.select("m", F.least(F.greatest(strength, F.lit(1.0)), F.lit(1e6)).alias("strength"))
    rate = (F.col("n_failed") + F.col("m") * F.col("strength")) / (F.col("n_docs") + F.col("strength"))
    out = per.crossJoin(F.broadcast(prior)).select("host", "n_docs", "n_failed", rate.alias("shrunk_rate"))
    return out.withColumn("host_rejected", F.col("shrunk_rate") > max_rate)


def judge(rows: DataFrame, host: str = "source", max_rate: float = MAX_HOST_RATE) -> DataFrame:
    """``rows`` (with base_failed) and their host's shrunk_rate, host_rejected; ``kept`` is the verdict.

    The host table is written first, so the planner knows its size: it is broadcast only under Spark's own limit, and
    beyond it both sides are shuffled and a hot host's part is split.
    """
    verdicts = stage(host_verdicts(rows, host, max_rate=max_rate), "host-verdicts")
    verdicts = verdicts.select(F.col("host").alias("host_"), "shrunk_rate", "host_rejected")
    joined = rows.join(verdicts, F.col(host).eqNullSafe(F.col("host_")), "left").drop("host_")
    return joined.withColumn("kept", ~F.col("base_failed") & ~F.coalesce(F.col("host_rejected"), F.lit(False)))


def quality(docs: DataFrame, max_rate: float = MAX_HOST_RATE) -> DataFrame:
    """The measures and the verdict of each document; text null or empty: no words, which fails.

    Repeated rows count as often as they are there.  Other columns are ignored.  Empty tables give empty results.
    """
    rows = clean_columns(docs, "doc_id", "text", "source")
    rows = _measured(rows, "text").drop("text").withColumn("base_failed", base_failed())
    rows = stage(rows, "quality-measures")
    out = judge(rows, max_rate=max_rate)
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "source", "shrunk_rate")


def keep_good(docs: DataFrame, max_rate: float = MAX_HOST_RATE) -> DataFrame:
    """The rows of ``docs`` that are kept, with all their columns (whatever those are called).

    Rows with null or empty texts fail and go, a null source is a host of its own, rows that repeat stay or go together,
    and an empty table gives an empty result.  Texts are measured once: the rows are written with their base verdict,
    and hosts are judged from that.
    """
    columns = docs.columns
    plain = docs.select(*(F.col(f"`{c}`").alias(f"in_{i}_") for i, c in enumerate(columns)), F.col("text").alias("text_"), F.col("source").alias("source_"))
    rows = _measured(plain, "text_").withColumn("base_failed", base_failed())
    rows = stage(rows.select(*(f"in_{i}_" for i in range(len(columns))), "source_", "base_failed"), "quality-rows")
    kept = judge(rows, host="source_", max_rate=max_rate).filter("kept")
    return kept.select(*(F.col(f"in_{i}_").alias(c) for i, c in enumerate(columns)))
