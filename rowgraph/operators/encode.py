"""Column encoders.  Statistics are fitted on rows up to the validation time and are a few numbers per column."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from datetime import datetime

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.columns import visible_at


@dataclass
class Numeric:
    """z-score with a null flag: null is 0 with flag 1."""

    column: str
    mean: float = 0.0
    std: float = 1.0

    def stats(self) -> list[Column]:
        c = F.col(self.column).cast("double")
        return [F.avg(c), F.stddev_pop(c)]

    def fitted(self, values: list) -> Numeric:
        return Numeric(self.column, values[0] or 0.0, values[1] or 1.0)

    def columns(self) -> list[Column]:
        c = F.col(self.column).cast("double")
        return [F.coalesce((c - self.mean) / self.std, F.lit(0.0)), c.isNull().cast("double")]


@dataclass
class Bins:
    """One-hot of quantile bins, and a place for null; a value on a cut is in the bin above."""

    column: str
    size: int = 8
    cuts: list = field(default_factory=list)

    def fit(self, df: DataFrame) -> Bins:
        got = df.agg(F.percentile(F.col(self.column).cast("double"), [i / self.size for i in range(1, self.size)])).first()[0]
        return Bins(self.column, self.size, list(got or []))

    def columns(self) -> list[Column]:
        c = F.col(self.column).cast("double")
        place = sum(((c >= x).cast("int") for x in self.cuts), F.lit(0))
        return [F.coalesce((place == i).cast("double"), F.lit(0.0)) for i in range(self.size)] + [c.isNull().cast("double")]


@dataclass
class Category:
    """One-hot of the known values with one place for the rest, or ``hashed`` places by md5."""

    column: str
    size: int = 32
    hashed: bool = False
    values: list = field(default_factory=list)

    def fit(self, df: DataFrame) -> Category:
        if self.hashed:
            return self
        top = df.groupBy(self.column).count().orderBy(F.desc("count"), self.column).limit(self.size)
        return Category(self.column, self.size, False, [r[0] for r in top.collect() if r[0] is not None])

    def columns(self) -> list[Column]:
        c = F.col(self.column).cast("string")
        if self.hashed:
            place = F.pmod(F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("bigint"), F.lit(self.size))
            return [F.coalesce((place == i).cast("double"), F.lit(0.0)) for i in range(self.size)]
        known = [F.coalesce((c == str(v)).cast("double"), F.lit(0.0)) for v in self.values]
        return [*known, (~F.coalesce(c.isin([str(v) for v in self.values]), F.lit(False))).cast("double")] if known else [F.lit(1.0)]


@dataclass
class TimeParts:
    """Month and weekday on the circle, and age in years at the seed time where there is one."""

    column: str
    at: str | None = None

    def columns(self) -> list[Column]:
        c = F.col(self.column)
        turn = lambda x, n: [F.coalesce(f(x * (6.283185307179586 / n)), F.lit(0.0)) for f in (F.sin, F.cos)]
        out = [*turn(F.month(c), 12), *turn(F.dayofweek(c), 7)]
        if self.at:
            out.append(F.coalesce(F.datediff(F.col(self.at), c) / 365.0, F.lit(0.0)))
        return out


@dataclass
class Span:
    """An interval: its length, and its age and whether it is open at a moment."""

    start: str
    end: str
    at: str | None = None

    def columns(self) -> list[Column]:
        a, b = F.col(self.start), F.col(self.end)
        out = [F.coalesce(F.datediff(b, a) / 30.0, F.lit(0.0))]
        if self.at:
            t = F.col(self.at)
            out += [F.coalesce(F.datediff(t, a) / 365.0, F.lit(0.0)), F.coalesce(((a <= t) & (t < b)).cast("double"), F.lit(0.0))]
        return out


@dataclass
class Text:
    """Hashed counts of words or of character n-grams, scaled by length."""

    column: str
    size: int = 64
    chars: int = 0

    def columns(self) -> list[Column]:
        c = F.lower(F.coalesce(F.col(self.column), F.lit("")))
        if self.chars:
            n = F.greatest(F.length(c) - self.chars + 1, F.lit(1))
            parts = F.transform(F.sequence(F.lit(1), n), lambda i: F.substr(c, i, F.lit(self.chars)))
        else:
            parts = F.filter(F.split(c, r"\s+"), lambda w: w != "")
        places = F.transform(parts, lambda w: F.pmod(F.xxhash64(w), F.lit(self.size)))
        total = F.greatest(F.size(parts), F.lit(1))
        return [F.size(F.filter(places, lambda p, k=i: p == k)) / total for i in range(self.size)]


@dataclass
class Vector:
    """A stored vector, as it is."""

    column: str
    size: int

    def columns(self) -> list[Column]:
        return [F.coalesce(F.get(F.col(self.column), F.lit(i)).cast("double"), F.lit(0.0)) for i in range(self.size)]


def pretrained(fn: Callable[[pd.Series], pd.Series], make: Callable[[], object] | None = None):
    """A pandas UDF for a plugged model over text or image bytes; ``make`` loads it once per worker."""

    @F.pandas_udf("array<float>")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = make() if make else None
        for s in batches:
            yield fn(s) if model is None else fn(model, s)

    return encode


class TableEncoder:
    """All encoders of a table; an encoder may be shared by columns (share) or own."""

    def __init__(self, encoders: list):
        self.encoders = encoders

    def fit(self, df: DataFrame, time: str | None = None, upto: datetime | None = None) -> TableEncoder:
        if time and upto:
            df = df.filter(visible_at(F.col(time), F.lit(upto).cast("timestamp_ntz")))
        numeric = [e for e in self.encoders if isinstance(e, Numeric)]
        got = list(df.agg(*(c for e in numeric for c in e.stats())).first()) if numeric else []
        out = []
        for e in self.encoders:
            if isinstance(e, Numeric):
                out.append(e.fitted(got[:2]))
                got = got[2:]
            else:
                out.append(e.fit(df) if isinstance(e, (Category, Bins)) else e)
        return TableEncoder(out)

    def transform(self, df: DataFrame, keep: list[str], out: str = "x") -> DataFrame:
        """keep and ``out``, an array<float> with all encoded columns (fused later by a linear map)."""
        return df.select(*keep, F.array(*(c.cast("float") for e in self.encoders for c in e.columns())).alias(out))

    def materialize(self, df: DataFrame, keep: list[str], path: str) -> DataFrame:
        """Encoded once, stored, and read from there: frozen features."""
        self.transform(df, keep).write.mode("overwrite").parquet(path)
        return df.sparkSession.read.parquet(path)


def html_text(column: str) -> Column:
    """Visible text of a page: scripts and styles out, tags to spaces, white space squeezed."""
    bare = F.regexp_replace(F.col(column), r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, r"(?s)<[^>]*>", " "), r"\s+", " "))


def tf_idf(df: DataFrame, column: str, size: int = 256, out: str = "tf_idf") -> DataFrame:
    """``df`` with hashed term weights of the ML library (a vector column)."""
    from pyspark.ml.feature import IDF, HashingTF

    words = df.withColumn("words_", F.filter(F.split(F.lower(F.coalesce(F.col(column), F.lit(""))), r"\s+"), lambda w: w != ""))
    counted = HashingTF(inputCol="words_", outputCol="tf_", numFeatures=size).transform(words)
    return IDF(inputCol="tf_", outputCol=out).fit(counted).transform(counted).drop("words_", "tf_")


def word_vectors(df: DataFrame, column: str, size: int = 16, out: str = "vector", min_count: int = 5) -> DataFrame:
    """``df`` with the mean of its words' vectors, fitted by the ML library."""
    from pyspark.ml.feature import Word2Vec

    words = df.withColumn("words_", F.filter(F.split(F.lower(F.coalesce(F.col(column), F.lit(""))), r"\s+"), lambda w: w != ""))
    return Word2Vec(vectorSize=size, minCount=min_count, inputCol="words_", outputCol=out, seed=1, maxIter=1).fit(words).transform(words).drop("words_")
