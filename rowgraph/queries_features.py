"""Queries on encoders, baselines, functions, sets, streams and training."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import columns as C
from .operators import baselines, encode, metrics, sampling, train
from .plans import timeline, workloads
from .queries_tasks import ORACLE as TASK_SQL
from .registry import BOUGHT, registry
from .sources.datasets import open_retail, purchases, table
from .sources.scratch import fresh_path
from .streaming import stream

QUERIES, ORACLE, query = registry()
S = SparkSession
AT = "TIMESTAMP '2000-07-01'"


def _at() -> F.Column:
    return F.lit(datetime(2000, 7, 1)).cast("timestamp_ntz")


# ------------------------------------------------------------------------------------ encoders


@query("enc_numeric", "WITH s AS (SELECT avg(c_acctbal) AS m, stddev_pop(c_acctbal) AS d FROM customer) SELECT c_custkey, round((c_acctbal - m) / d, 6) AS z, 0 AS missing FROM customer, s")
def enc_numeric(spark: S, d: str) -> DataFrame:
    df = table(spark, d, "customer")
    fitted = encode.TableEncoder([encode.Numeric("c_acctbal")]).fit(df)
    z, missing = fitted.encoders[0].columns()
    return df.select("c_custkey", F.round(z, 6).alias("z"), missing.cast("int").alias("missing"))


@query("enc_category", "SELECT c_custkey, (dense_rank() OVER (ORDER BY n DESC, c_mktsegment))::INT AS place FROM customer JOIN (SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY 1) USING (c_mktsegment)")
def enc_category(spark: S, d: str) -> DataFrame:
    df = table(spark, d, "customer")
    hot = F.array(*encode.Category("c_mktsegment").fit(df).columns())
    return df.select("c_custkey", F.array_position(hot, 1.0).cast("int").alias("place"))


@query("enc_text_stats", r"SELECT doc_id, length(text) AS n_chars, len(list_filter(regexp_split_to_array(lower(text), '\s+'), lambda w: w <> '')) AS n_words FROM documents")
def enc_text_stats(spark: S, d: str) -> DataFrame:
    words = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
    return table(spark, d, "documents").select("doc_id", F.length("text").cast("bigint").alias("n_chars"), F.size(words).cast("bigint").alias("n_words"))


@query("token_tf", r"SELECT lang, w AS token, count(*) AS n, count(DISTINCT doc_id) AS n_docs FROM (SELECT doc_id, lang, unnest(regexp_split_to_array(lower(text), '[^a-z]+')) AS w FROM documents) WHERE length(w) > 2 GROUP BY ALL HAVING count(*) >= 50")
def token_tf(spark: S, d: str) -> DataFrame:
    words = table(spark, d, "documents").select("doc_id", "lang", F.explode(F.split(F.lower("text"), "[^a-z]+")).alias("token")).filter(F.length("token") > 2)
    # per document first, so that neither count needs a distinct over all words
    per = words.groupBy("lang", "token", "doc_id").agg(F.count("*").alias("c"))
    return per.groupBy("lang", "token").agg(F.sum("c").alias("n"), F.count("*").alias("n_docs")).filter("n >= 50")


@query("enc_vector_norm", "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 5) AS norm FROM embeddings")
def enc_vector_norm(spark: S, d: str) -> DataFrame:
    return table(spark, d, "embeddings").select("vec_id", F.round(C.norm(F.col("embedding")), 5).alias("norm"))


@query("enc_time", "SELECT o_orderkey, month(o_orderdate)::INT AS m, (dayofweek(o_orderdate) + 1)::INT AS wd, round(sin(month(o_orderdate) * (6.283185307179586::DOUBLE / 12)), 6) AS ms, date_diff('day', o_orderdate, TIMESTAMP '2000-07-01')::INT AS age FROM orders")
def enc_time(spark: S, d: str) -> DataFrame:
    ts = F.col("o_orderdate")
    sine = encode.TimeParts("o_orderdate").columns()[0]
    return table(spark, d, "orders").select("o_orderkey", F.month(ts).alias("m"), F.dayofweek(ts).alias("wd"), F.round(sine, 6).alias("ms"), F.datediff(_at(), ts).alias("age"))


@query("enc_span", f"SELECT l_orderkey, l_linenumber, round(date_diff('day', o_orderdate, l_shipdate) / 30.0::DOUBLE, 6) AS months, (o_orderdate <= {AT} AND {AT} < l_shipdate)::INT AS open_ FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def enc_span(spark: S, d: str) -> DataFrame:
    rows = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).withColumn("t", _at())
    months, _, open_ = encode.Span("o_orderdate", "l_shipdate", "t").columns()
    return rows.select("l_orderkey", "l_linenumber", F.round(months, 6).alias("months"), open_.cast("int").alias("open_"))


@query("props_value", "SELECT event_id, (props::JSON->>'$.k')::INT AS k FROM events")
def props_value(spark: S, d: str) -> DataFrame:
    return table(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("page_host", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, length(regexp_replace(html, '<[^>]*>', '', 'g')) AS n_text FROM pages")
def page_host(spark: S, d: str) -> DataFrame:
    return table(spark, d, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host"), F.length(F.regexp_replace("html", "<[^>]*>", "")).cast("bigint").alias("n_text"))


@query("link_dot_score", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)), 4) AS score FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def link_dot_score(spark: S, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    a = e.select(F.col("vec_id").alias("a"), F.col("embedding").alias("va"))
    b = e.select(F.col("vec_id").alias("b"), (F.col("vec_id") - 1).alias("a"), F.col("embedding").alias("vb"))
    return a.join(b, "a").select("a", "b", F.round(C.dot(F.col("va"), F.col("vb")), 4).alias("score"))


# ------------------------------------------------------------------------------------ hand features


_W = (7, 30, 90, 365)
_FEATS = ", ".join(f"count(ts) FILTER (ts > seed_time - INTERVAL {w} DAY) AS n_{w}, CAST(coalesce(sum(CAST(p_retailprice AS DECIMAL(18,2))) FILTER (ts > seed_time - INTERVAL {w} DAY), 0) AS DOUBLE) AS sum_{w}" for w in _W)
_TASK = f"t AS ({TASK_SQL['customer_churn']})"
_PAST = f"WITH {_TASK}, {BOUGHT} "
_FROM = " FROM t LEFT JOIN bought USING (c_custkey) WHERE ts <= seed_time AND ts > seed_time - INTERVAL 365 DAY GROUP BY split, seed_time, c_custkey"


def _stamps(spark: S) -> DataFrame:
    return timeline.stamps(spark, workloads.RETAIL, 365, min_history=365)


@query("feat_recent", _PAST + f"SELECT split, seed_time, c_custkey, {_FEATS}" + _FROM)
def feat_recent(spark: S, d: str) -> DataFrame:
    return baselines.recent_features(workloads.customer_churn(spark, d), purchases(spark, d), "c_custkey", "p_retailprice", _W, _stamps(spark))


_WEEK = ", ".join(f"count(*) FILTER (dayofweek(ts) = {k - 1}) AS n_d{k}, CAST(coalesce(sum(CAST(p_retailprice AS DECIMAL(18,2))) FILTER (dayofweek(ts) = {k - 1}), 0) AS DOUBLE) AS sum_d{k}" for k in range(1, 8))


@query("feat_weekday", _PAST + f"SELECT split, seed_time, c_custkey, {_WEEK}" + _FROM)
def feat_weekday(spark: S, d: str) -> DataFrame:
    return baselines.weekday_features(workloads.customer_churn(spark, d), purchases(spark, d), "c_custkey", "p_retailprice", stamps=_stamps(spark))


@query(
    "feat_daily",
    """WITH s AS (SELECT TIMESTAMP '2024-01-08' + INTERVAL 1 DAY * k AS seed_time FROM range(0, 22) r(k))
SELECT seed_time, user_id, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS total FROM events JOIN s ON ts <= seed_time AND ts > seed_time - INTERVAL 7 DAY GROUP BY ALL""",
)
def feat_daily(spark: S, d: str) -> DataFrame:
    """The same features again for every day: each event meets the seven stamps that it matters to by arithmetic."""
    events = table(spark, d, "events").select("user_id", "ts", "value")
    hit = timeline.matching_stamps(events, "ts", datetime(2024, 1, 8), 1, 22, 7, 0)
    return hit.groupBy("seed_time", "user_id").agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).cast("double").alias("total"))


@query(
    "feat_rolling",
    """SELECT event_id, count(*) OVER w AS n_before, CAST(coalesce(sum(CAST(value AS DECIMAL(18,2))) OVER w, 0) AS DOUBLE) AS total_before FROM (SELECT *, epoch(ts)::BIGINT AS sec FROM events)
WINDOW w AS (PARTITION BY user_id ORDER BY sec RANGE BETWEEN 604800 PRECEDING AND 1 PRECEDING)""",
)
def feat_rolling(spark: S, d: str) -> DataFrame:
    """Frames end a second before the row, so it never sees itself; times count to the nearest second."""
    w = Window.partitionBy("user_id").orderBy(F.col("sec").asc_nulls_last()).rangeBetween(-604800, -1)
    rows = table(spark, d, "events").withColumn("sec", C.nearest_second(F.col("ts")))
    return rows.select("event_id", F.count("*").over(w).alias("n_before"), F.coalesce(F.sum(F.col("value").cast("decimal(18,2)")).over(w), F.lit(0)).cast("double").alias("total_before"))


@query("flat_table", _PAST + f", f AS (SELECT split, seed_time, c_custkey, {_FEATS}" + _FROM + ") SELECT t.*, c_acctbal, c_mktsegment, n_7, sum_7, n_30, sum_30, n_90, sum_90, n_365, sum_365 FROM t JOIN customer USING (c_custkey) LEFT JOIN f USING (split, seed_time, c_custkey)")
def flat_table(spark: S, d: str) -> DataFrame:
    task = workloads.customer_churn(spark, d)
    recent = baselines.recent_features(task, purchases(spark, d), "c_custkey", "p_retailprice", _W, _stamps(spark))
    return baselines.flat_table(task, table(spark, d, "customer"), "c_custkey", ["c_acctbal", "c_mktsegment"], recent)


# ------------------------------------------------------------------------------------ functions, sets, top-k


@query("fn_string", "SELECT c_custkey, lower(c_name) AS lo, split_part(c_name, '#', 2) AS tail, length(c_name) AS n, md5(c_name) AS h, regexp_extract(c_name, '([0-9]+)', 1) AS digits, levenshtein(c_name, c_mktsegment) AS dist FROM customer")
def fn_string(spark: S, d: str) -> DataFrame:
    n = F.col("c_name")
    return table(spark, d, "customer").select("c_custkey", F.lower(n).alias("lo"), F.split_part(n, F.lit("#"), F.lit(2)).alias("tail"), F.length(n).cast("bigint").alias("n"), F.md5(n).alias("h"), F.regexp_extract(n, "([0-9]+)", 1).alias("digits"), F.levenshtein(n, "c_mktsegment").cast("bigint").alias("dist"))


@query("fn_date", "SELECT o_orderkey, date_trunc('month', o_orderdate)::TIMESTAMP AS m, o_orderdate + INTERVAL 6 MONTH AS half, year(o_orderdate)::INT AS y, date_diff('day', o_orderdate, TIMESTAMP '2000-07-01')::INT AS age FROM orders")
def fn_date(spark: S, d: str) -> DataFrame:
    t = F.col("o_orderdate")
    return table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", t).cast("timestamp_ntz").alias("m"), (t + F.expr("interval 6 month")).alias("half"), F.year(t).alias("y"), F.datediff(_at(), t).alias("age"))


@query("fn_array", "SELECT o_custkey, len(list(o_orderkey)) AS n, list_sort(list(o_orderkey))[1] AS lo, list_sum(list_transform(list(o_orderkey), lambda x: x % 7))::BIGINT AS s, len(list_filter(list(o_orderkey), lambda x: x % 2 = 0)) AS evens FROM orders GROUP BY o_custkey")
def fn_array(spark: S, d: str) -> DataFrame:
    keys = table(spark, d, "orders").groupBy("o_custkey").agg(F.collect_list("o_orderkey").alias("k"))
    total = F.aggregate(F.transform("k", lambda x: x % 7), F.lit(0).cast("bigint"), lambda s, x: s + x)
    return keys.select("o_custkey", F.size("k").cast("bigint").alias("n"), F.array_sort("k")[0].alias("lo"), total.alias("s"), F.size(F.filter("k", lambda x: x % 2 == 0)).cast("bigint").alias("evens"))


@query("fn_map", "SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds, max(n) AS top FROM (SELECT user_id, event_type, count(*) OVER (PARTITION BY user_id, event_type) AS n FROM events) GROUP BY user_id")
def fn_map(spark: S, d: str) -> DataFrame:
    per = table(spark, d, "events").groupBy("user_id", "event_type").count()
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size(F.map_keys("m")).cast("bigint").alias("kinds"), F.array_max(F.map_values("m")).alias("top"))


@query("fn_json", "SELECT event_type, sum((props::JSON->>'$.k')::BIGINT)::BIGINT AS total, max((props::JSON->>'$.k')::INT) AS top FROM events GROUP BY event_type")
def fn_json(spark: S, d: str) -> DataFrame:
    k = F.get_json_object("props", "$.k").cast("int")
    return table(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("total"), F.max(k).alias("top"))


@query("fn_vec", "SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)) / (sqrt(list_sum(list_transform(a.embedding, lambda x: x::DOUBLE * x::DOUBLE))) * sqrt(list_sum(list_transform(b.embedding, lambda x: x::DOUBLE * x::DOUBLE)))), 5) AS cosine FROM embeddings a, (SELECT embedding FROM embeddings ORDER BY vec_id LIMIT 1) b")
def fn_vec(spark: S, d: str) -> DataFrame:
    """Cosine of every vector with that of the smallest id."""
    e = table(spark, d, "embeddings")
    first = e.agg(F.min_by("embedding", "vec_id").alias("b"))
    return e.crossJoin(F.broadcast(first)).select("vec_id", F.round(C.cosine(F.col("embedding"), F.col("b")), 5).alias("cosine"))


_OLD, _NEW = "o_orderdate < TIMESTAMP '1998-01-01'", "o_orderdate >= TIMESTAMP '1998-01-01'"


def _buyers(spark: S, d: str, old: bool) -> DataFrame:
    limit = F.lit(datetime(1998, 1, 1)).cast("timestamp_ntz")
    t = F.col("o_orderdate")
    return table(spark, d, "orders").filter(t < limit if old else t >= limit).select("o_custkey")


@query("set_union", f"SELECT o_custkey FROM orders WHERE {_OLD} UNION SELECT o_custkey FROM orders WHERE {_NEW}")
def set_union(spark: S, d: str) -> DataFrame:
    return _buyers(spark, d, True).union(_buyers(spark, d, False)).distinct()


@query("set_intersect", f"SELECT o_custkey FROM orders WHERE {_OLD} INTERSECT SELECT o_custkey FROM orders WHERE {_NEW}")
def set_intersect(spark: S, d: str) -> DataFrame:
    return _buyers(spark, d, True).intersect(_buyers(spark, d, False))


@query("set_except", f"SELECT o_custkey FROM orders WHERE {_OLD} EXCEPT ALL SELECT o_custkey FROM orders WHERE {_NEW}")
def set_except(spark: S, d: str) -> DataFrame:
    return _buyers(spark, d, True).exceptAll(_buyers(spark, d, False))


@query("topk_parts", "SELECT p_brand, p_partkey, n FROM (SELECT p_brand, p_partkey, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL) QUALIFY row_number() OVER (PARTITION BY p_brand ORDER BY n DESC, p_partkey) <= 5")
def topk_parts(spark: S, d: str) -> DataFrame:
    sold = table(spark, d, "lineitem").groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.count("*").alias("n"))
    named = sold.join(table(spark, d, "part").select("p_partkey", "p_brand"), "p_partkey")
    return sampling.pick(named, ["p_brand"], 5, [F.desc("n"), F.col("p_partkey")]).select("p_brand", "p_partkey", "n")


@query(
    "session_islands",
    """WITH g AS (SELECT *, CASE WHEN epoch(ts)::BIGINT - epoch(lag(ts) OVER w)::BIGINT < 86400 THEN 0 ELSE 1 END AS new_ FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
b AS (SELECT *, sum(new_) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS burst FROM g)
SELECT user_id, burst::BIGINT AS burst, min(ts) AS started, max(ts) AS ended, count(*) AS n FROM b GROUP BY ALL""",
)
def session_islands(spark: S, d: str) -> DataFrame:
    return stream.batch_bursts(table(spark, d, "events"), "user_id", 86400, C.nearest_second(F.col("ts")))


@query(
    "reservoir_replace",
    f"""WITH e AS (SELECT o_custkey AS dst, o_orderkey AS child, exp(-0.6931471805599453::DOUBLE * date_diff('day', o_orderdate, {AT}) / 365.0::DOUBLE) AS w FROM orders WHERE o_orderdate <= {AT}),
c AS (SELECT *, sum(w) OVER (PARTITION BY dst ORDER BY child ROWS UNBOUNDED PRECEDING) AS hi, sum(w) OVER (PARTITION BY dst) AS total FROM e),
u AS (SELECT *, (('0x' || substr(md5('s1|' || dst || '|' || j), 1, 13))::BIGINT + 0.5::DOUBLE) / {float(16**13)!r}::DOUBLE * total AS mark FROM c, (SELECT unnest([1, 2, 3, 4]) AS j))
SELECT dst, j, child FROM u WHERE mark >= hi - w AND mark < hi""",
)
def reservoir_replace(spark: S, d: str) -> DataFrame:
    """Four draws with replacement from each customer's visible orders, by recency."""
    rows = table(spark, d, "orders").filter(F.col("o_orderdate") <= _at()).select(F.col("o_custkey").alias("dst"), F.col("o_orderkey").alias("child"), F.col("o_orderdate").alias("ts"))
    drawn = sampling.with_replacement(rows, ["dst"], 4, C.recency_weight(F.col("ts"), _at(), 365.0))
    return drawn.select("dst", "j", "child")


# ------------------------------------------------------------------------------------ streams


def _as_stream(spark: S, d: str, chunks: int = 4) -> DataFrame:
    """The events as a feed: a few files, written one after the other in order of time, and read one at a time."""
    path = fresh_path(spark, "stream")
    events = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    lo, hi = events.agg(F.min("ts"), F.max("ts")).first()
    for k in range(chunks):
        # a stream reads files in the order of their times, so a chunk is a file
        part = F.floor((F.unix_micros("ts") - F.unix_micros(F.lit(lo))) * chunks / (F.unix_micros(F.lit(hi)) - F.unix_micros(F.lit(lo)) + 1))
        events.filter(part == k).coalesce(1).write.mode("append").parquet(path)
    return stream.read_facts(spark, path, events.schema, files=1)


@query("stream_labels", "SELECT time_bucket(INTERVAL 2 DAY, ts, TIMESTAMP '1970-01-01') AS seed_time, user_id, count(*) AS n FROM events WHERE event_type = 'purchase' AND ts < (SELECT time_bucket(INTERVAL 2 DAY, max(ts) - INTERVAL 1 HOUR, TIMESTAMP '1970-01-01') FROM events WHERE event_type = 'purchase') GROUP BY ALL")
def stream_labels(spark: S, d: str) -> DataFrame:
    """Mature two-day purchase counts: windows that end after the watermark aren't given out."""
    facts = _as_stream(spark, d).filter("event_type = 'purchase'")
    out = stream.mature_labels(facts, "user_id", "2 days", "1 hour", {"n": F.count("*")})
    got = stream.to_files(out, fresh_path(spark, "stream-labels"))
    return got.select(F.col("seed_time").cast("timestamp_ntz").alias("seed_time"), "user_id", "n")


@query("stream_latest", "SELECT user_id, string_agg(event_id, ',' ORDER BY ts DESC, event_id) AS items FROM (SELECT * FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id) <= 5) GROUP BY user_id")
def stream_latest(spark: S, d: str) -> DataFrame:
    """Each user's five latest events as state of a stream that comes in several batches."""
    out = stream.latest_neighbours(_as_stream(spark, d), "user_id", "event_id", 5, "30 days")
    got = stream.to_files(out, fresh_path(spark, "stream-latest"), mode="update")
    return got.groupBy("user_id").agg(F.max_by("items", "version").alias("items"))


# ------------------------------------------------------------------------------------ training


def _planted(spark: S, n: int, label: str, loss: str, steps: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Scores of a trained two-hop model on unseen entities, the flat table of the entity's own columns, and its unseen part."""
    from .plans.tasks import static_split
    from .sources.io import open_planted

    db, task = open_planted(spark, n)
    task = task.select("id", "seed_time", F.col(label).alias("label"), static_split(F.col("id")).alias("split")).cache()
    seeds = sampling.seeds_of(task, "id", "entity").join(task.select(F.col("id").alias("nid"), "label", "split"), "nid")
    cut = sampling.cut_slice(db, seeds.select("seed_id", "seed_time", "ntype", "nid"), [4, 4], sampling.Strategy("latest"), [("fact.entity", True), ("fact.item", False)])
    arr = lambda *c: F.array(*(F.col(x).cast("float") for x in c)).alias("x")
    feats = {"entity": db["entity"].select(F.col("id").alias("nid"), arr("x")), "fact": db["fact"].select(F.col("id").alias("nid"), F.array(F.lit(1.0).cast("float")).alias("x")), "item": db["item"].select(F.col("id").alias("nid"), arr("good", "y"))}
    packed = train.pack_features(cut, seeds, feats).join(seeds.select("seed_id", "split"), "seed_id").repartition(4, "seed_id").cache()
    model = train.Model("entity", {"entity": 1, "fact": 1, "item": 2}, [("fact.entity", "entity"), ("fact.item^", "fact")], d=8, loss=loss).init(3)
    train.fit([model], [packed.filter("split = 'train'").drop("split")], steps=steps, rate=0.05)
    flat = task.join(db["entity"], "id")
    return train.predict(model, packed.filter("split <> 'train'").drop("split")), flat, flat.filter("split <> 'train'")


def planted_models(spark: S, n: int = 400, steps: int = 60) -> list[tuple[str, float]]:
    """(model, average precision on unseen entities) where the label is decided two hops away."""
    scored, flat, rest = _planted(spark, n, "label", "logistic", steps)
    boosted = baselines.boosted_scores(baselines.fit_boosted(flat, "label", "binary", ["x"], trees=5, depth=2), rest, "binary")
    found = {"two hops": scored, "entity only": boosted, "base rate": rest.withColumn("score", F.lit(0))}
    return [(name, metrics.average_precision(rows).first()["ap"]) for name, rows in found.items()]


def planted_values(spark: S, n: int = 400, steps: int = 50) -> list[tuple[str, float]]:
    """(model, mean absolute error on unseen entities) where the value is decided two hops away."""
    scored, flat, rest = _planted(spark, n, "amount", "squared", steps)
    boosted = baselines.boosted_scores(baselines.fit_boosted(flat, "label", "regression", ["x"], trees=5, depth=2), rest, "regression")
    middle = baselines.constant(flat).filter("split <> 'train'").withColumn("score", F.col("y_hat"))
    found = {"two hops": scored, "entity only": boosted, "median": middle}
    return [(name, metrics.mean_abs_error(rows.drop("y_hat").withColumnRenamed("score", "y_hat")).first()["mae"]) for name, rows in found.items()]


@query("train_planted")
def train_planted(spark: S, d: str) -> DataFrame:
    return spark.createDataFrame(planted_models(spark), "model string, ap double")


@query("train_planted_value")
def train_planted_value(spark: S, d: str) -> DataFrame:
    return spark.createDataFrame(planted_values(spark), "model string, mae double")


@query("text_quality")
def text_quality(spark: S, d: str) -> DataFrame:
    """Document quality from hashed words and size, boosted trees, with the base rate (static task)."""
    task = workloads.static_quality(spark, d)
    docs = table(spark, d, "documents")
    coded = encode.TableEncoder([encode.Numeric("n_chars"), encode.Text("text", 16)]).fit(docs).transform(docs, ["doc_id"])
    size = 18
    flat = task.join(coded, "doc_id").select("split", "doc_id", "label", *(F.col("x")[i].cast("double").alias(f"x{i}") for i in range(size))).cache()
    rest, out = flat.filter("split <> 'train'"), []
    fitted = baselines.fit_boosted(flat, "label", "binary", [f"x{i}" for i in range(size)], trees=5, depth=3)
    out.append(("boosted text", metrics.average_precision(baselines.boosted_scores(fitted, rest, "binary")).first()["ap"]))
    out.append(("base rate", metrics.average_precision(rest.withColumn("score", F.lit(0))).first()["ap"]))
    flat.unpersist()
    return spark.createDataFrame(out, "model string, ap double")


@query("metric_f1_static", "WITH t AS (SELECT doc_id, quality AS a, (n_chars > 200)::INT AS b FROM labels JOIN documents USING (doc_id)), c AS (SELECT k, (SELECT count(*) FROM t WHERE a = k) AS ta, (SELECT count(*) FROM t WHERE b = k) AS tb, (SELECT count(*) FROM t WHERE a = k AND b = k) AS hit FROM (VALUES (0), (1)) v(k)) SELECT round(avg(2.0::DOUBLE * hit / (ta + tb)), 9) AS macro_f1 FROM c WHERE ta > 0")
def metric_f1_static(spark: S, d: str) -> DataFrame:
    rows = table(spark, d, "labels").join(table(spark, d, "documents").select("doc_id", "n_chars"), "doc_id").select(F.col("quality").alias("label"), (F.col("n_chars") > 200).cast("int").alias("y_hat"))
    return metrics.macro_f1(rows).select(F.round("macro_f1", 9).alias("macro_f1"))


@query("retail_visible", f"SELECT (SELECT count(*) FROM orders WHERE o_orderdate <= {AT}) AS n_orders, (SELECT count(*) FROM lineitem WHERE l_shipdate <= {AT}) AS n_lines")
def retail_visible(spark: S, d: str) -> DataFrame:
    db = open_retail(spark, d).visible(datetime(2000, 7, 1))
    a = db["orders"].agg(F.count("*").alias("n_orders"))
    return a.crossJoin(F.broadcast(db["lineitem"].agg(F.count("*").alias("n_lines"))))
