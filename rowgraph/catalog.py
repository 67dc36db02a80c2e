"""Linked databases: tables, keys, links, roles and modalities."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from datetime import datetime
from enum import Enum
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .functions.columns import visible_at


class Modality(str, Enum):
    NUMBER = "number"
    CATEGORY = "category"
    TEXT = "text"
    IMAGE = "image"
    TIME = "time"
    VECTOR = "vector"


@dataclass(frozen=True)
class TableSpec:
    """A table: its rows, one key column, time column if it has one, and role.  Foreign keys are links."""

    name: str
    df: DataFrame
    pk: str
    time: str | None = None
    role: str | None = None

    @property
    def spark(self) -> SparkSession:
        return self.df.sparkSession


@dataclass(frozen=True)
class LinkSpec:
    """Column ``fk`` of ``child`` holds keys of ``parent``."""

    child: str
    fk: str
    parent: str

    @property
    def name(self) -> str:
        return f"{self.child}.{self.fk}"


@dataclass(frozen=True)
class Database:
    tables: dict[str, TableSpec]
    links: tuple[LinkSpec, ...]
    notes: dict[str, str] = field(default_factory=dict)

    @classmethod
    def of(cls, tables: list[TableSpec], links: list[LinkSpec]) -> Database:
        named = {t.name: t for t in tables}
        for link in links:
            if link.child not in named or link.parent not in named:
                raise ValueError(f"link {link.name} -> {link.parent} names an unknown table")
            if link.fk not in named[link.child].df.columns:
                raise ValueError(f"{link.child} has no column {link.fk}")
        for t in tables:
            if t.pk not in t.df.columns or (t.time and t.time not in t.df.columns):
                raise ValueError(f"{t.name} lacks its key or time column")
        return cls(named, tuple(links))

    def __getitem__(self, name: str) -> DataFrame:
        return self.tables[name].df

    @property
    def spark(self) -> SparkSession:
        return next(iter(self.tables.values())).spark

    def visible(self, upto: datetime) -> Database:
        """The database as of a moment: rows with a later time are gone, rows without time stay."""
        t = F.lit(upto).cast("timestamp_ntz")
        return replace(self, tables={n: replace(s, df=s.df.filter(visible_at(F.col(s.time), t))) if s.time else s for n, s in self.tables.items()})

    def attach(self, name: str, task: DataFrame, keys: dict[str, str], pk: str, time: str | None = "seed_time") -> Database:
        """The database with a task table as one more table, linked by its key columns (column -> table)."""
        spec = TableSpec(name, task, pk, time if time in task.columns else None, "task")
        return Database.of([*self.tables.values(), spec], [*self.links, *(LinkSpec(name, c, t) for c, t in keys.items())])

    def register(self, prefix: str = "") -> list[str]:
        """Temporary views of all tables for SQL users."""
        for n, s in self.tables.items():
            s.df.createOrReplaceTempView(prefix + n)
        return [prefix + n for n in self.tables]

    def horizon(self, names: list[str]) -> tuple[datetime, datetime]:
        """Oldest and newest time of some tables: one row to the driver."""
        parts = [self[n].select(F.min(self.tables[n].time).alias("lo"), F.max(self.tables[n].time).alias("hi")) for n in names]
        row = reduce(DataFrame.unionByName, parts).agg(F.min("lo"), F.max("hi")).first()
        return row[0], row[1]


def check_keys(db: Database) -> DataFrame:
    """One row per check: repeated keys, null keys, and references without a row (null references are allowed)."""
    out = []
    for n, s in db.tables.items():
        keys = s.df.groupBy(s.pk).count()
        out.append(keys.agg(F.count(F.when(F.col(s.pk).isNotNull() & (F.col("count") > 1), 1)).alias("violations")).select(F.lit(n).alias("table"), F.lit("repeated key").alias("check"), "violations"))
        out.append(s.df.agg(F.count(F.when(F.col(s.pk).isNull(), 1)).alias("violations")).select(F.lit(n).alias("table"), F.lit("null key").alias("check"), "violations"))
    for link in db.links:
        parent = db.tables[link.parent]
        refs = db[link.child].select(F.col(link.fk).alias("k")).filter("k is not null")
        lost = refs.join(parent.df.select(F.col(parent.pk).alias("k")), "k", "left_anti")
        out.append(lost.agg(F.count("*").alias("violations")).select(F.lit(link.child).alias("table"), F.lit(f"{link.fk} not in {link.parent}").alias("check"), "violations"))
    return reduce(DataFrame.unionByName, out)


def classify_roles(db: Database, small: int = 1000) -> dict[str, str]:
    """fact: has a reference and a time and isn't small; dimension otherwise.  A declared role stands."""
    out = {}
    for n, s in db.tables.items():
        refers = any(link.child == n for link in db.links)
        out[n] = s.role or ("fact" if refers and s.time and s.df.limit(small + 1).count() > small else "dimension")
    return out


def infer_modalities(df: DataFrame, max_categories: int = 64) -> dict[str, Modality]:
    """From types and approximate distinct counts, in one pass."""
    text = [f.name for f in df.schema if isinstance(f.dataType, T.StringType)]
    kinds = df.agg(*(F.approx_count_distinct(c).alias(c) for c in text)).first().asDict() if text else {}
    out = {}
    for f in df.schema:
        if isinstance(f.dataType, T.StringType):
            out[f.name] = Modality.CATEGORY if kinds[f.name] <= max_categories else Modality.TEXT
        elif isinstance(f.dataType, T.NumericType):
            out[f.name] = Modality.NUMBER
        elif isinstance(f.dataType, (T.TimestampType, T.TimestampNTZType, T.DateType)):
            out[f.name] = Modality.TIME
        elif isinstance(f.dataType, T.ArrayType):
            out[f.name] = Modality.VECTOR
        else:
            out[f.name] = Modality.IMAGE
    return out


def infer_links(tables: list[TableSpec]) -> list[LinkSpec]:
    """Proposals for review: a column of the key's type whose name ends like the key's and whose values are all there."""
    out = []
    for child in tables:
        for parent in tables:
            if parent.name == child.name:
                continue
            tail, kind = parent.pk.split("_")[-1], parent.df.schema[parent.pk].dataType
            for f in child.df.schema:
                if f.name != child.pk and f.name.split("_")[-1] == tail and isinstance(kind, T.IntegralType) and isinstance(f.dataType, T.IntegralType):
                    lost = child.df.select(F.col(f.name).alias("k")).filter("k is not null").join(parent.df.select(F.col(parent.pk).alias("k")), "k", "left_anti")
                    if lost.isEmpty():
                        out.append(LinkSpec(child.name, f.name, parent.name))
    return out
