"""Sources and sinks."""

from __future__ import annotations

from collections.abc import Iterator
from datetime import datetime, timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

FORMATS = ("parquet", "csv", "json", "orc", "text", "binaryFile")


def read(spark: SparkSession, fmt: str, path: str, schema: T.StructType | str | None = None, **options) -> DataFrame:
    """A file source; csv and json need a schema, so that nothing is inferred by reading the data twice."""
    if fmt not in FORMATS:
        raise ValueError(f"{fmt} is none of {', '.join(FORMATS)}")
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"{fmt} needs a schema")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def jdbc_options(url: str, table: str, column: str, low: int, high: int, parts: int) -> dict[str, str]:
    """Options of a read that is cut into ranges of a column."""
    return {"url": url, "dbtable": table, "partitionColumn": column, "lowerBound": str(low), "upperBound": str(high), "numPartitions": str(parts)}


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, parts: int, **more) -> DataFrame:
    return spark.read.format("jdbc").options(**jdbc_options(url, table, column, low, high, parts), **more).load()


def write(df: DataFrame, path: str, partition_by: list[str] | None = None, mode: str = "errorifexists", fmt: str = "parquet") -> None:
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def write_bucketed(df: DataFrame, name: str, by: str, buckets: int, sort: list[str]) -> None:
    """A table whose later joins on ``by`` need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(*sort).saveAsTable(name)


# --------------------------------------------------------------------------------------------- planted signal


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _PlantedReader(DataSourceReader):
    def __init__(self, table: str, n: int, parts: int):
        self.table, self.n, self.parts = table, n, parts

    def partitions(self) -> list[_Range]:
        step = -(-self.n // self.parts)
        return [_Range(k, min(k + step, self.n)) for k in range(0, self.n, step)]

    def read(self, part: _Range) -> Iterator[tuple]:
        for i in range(part.low, part.high):
            yield from planted_rows(self.table, i)


def _noise(*parts: int) -> float:
    import hashlib

    return int.from_bytes(hashlib.md5(repr(parts).encode()).digest()[:6], "big") / 2**48


#: Planted linked data: every entity has three facts, each refers to one of ITEMS items, half of which are good.
ITEMS, FACTS = 40, 3
SEED_TIME = datetime(2000, 1, 1)


def is_good(item: int) -> bool:
    return _noise(7, item) < 0.5


def planted_rows(table: str, i: int) -> Iterator[tuple]:
    """entity: (id, x); fact: (id, entity, item, ts); item: (id, good, y); task: (id, seed_time, label, amount).

    The amount is the number of an entity's facts that refer to good items, which only the items say; the label is 1
    where those are most of them.
    """
    picks = [int(_noise(1, i, k) * ITEMS) for k in range(FACTS)]
    if table == "entity":
        yield i, _noise(2, i)
    elif table == "fact":
        for k, item in enumerate(picks):
            yield i * FACTS + k, i, item, SEED_TIME - timedelta(days=1 + k)
        # one row in the future, which must not be seen
        yield 10**9 + i, i, int(_noise(3, i) * ITEMS), SEED_TIME + timedelta(days=2)
    elif table == "item" and i < ITEMS:
        yield i, float(is_good(i)), _noise(4, i)
    elif table == "task":
        good = sum(map(is_good, picks))
        yield i, SEED_TIME, int(good * 2 > FACTS), float(good)


_SCHEMAS = {"entity": "id long, x double", "fact": "id long, entity long, item long, ts timestamp_ntz", "item": "id long, good double, y double", "task": "id long, seed_time timestamp_ntz, label int, amount double"}


class PlantedSource(DataSource):
    """spark.read.format("planted").option("table", ...).option("n", ...).load()"""

    @classmethod
    def name(cls) -> str:
        return "planted"

    def schema(self) -> str:
        return _SCHEMAS[self.options["table"]]

    def reader(self, schema) -> _PlantedReader:
        return _PlantedReader(self.options["table"], int(self.options.get("n", "500")), int(self.options.get("parts", "4")))


def open_planted(spark: SparkSession, n: int = 500):
    """The planted database and its task table."""
    from ..catalog import Database, LinkSpec, TableSpec

    spark.dataSource.register(PlantedSource)
    load = lambda t: spark.read.format("planted").option("table", t).option("n", str(n)).load()
    db = Database.of(
        [TableSpec("entity", load("entity"), "id"), TableSpec("fact", load("fact"), "id", "ts"), TableSpec("item", load("item"), "id")],
        [LinkSpec("fact", "entity", "entity"), LinkSpec("fact", "item", "item")],
    )
    return db, load("task")
