"""Writing and reading collections: file formats, bucketed tables and a Python data source."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from overlapix.functions import hashing as H

SCHEMAS = {
    "set": "id bigint, elems array<bigint>, f int",
    "incidence": "id bigint, e bigint",
    "bucket": "j int, key string, id bigint",
    "signature": "id bigint, f int, sig array<bigint>, pad array<boolean>",
    "gold": "q_id bigint, rank bigint, x_id bigint, a bigint",
}
FORMATS = ("parquet", "orc", "json", "csv")


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the folder that all executors share; a temporary one in local tests."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        root = f"file://{tempfile.gettempdir()}/overlapix-scratch"
    return f"{root.rstrip('/')}/{label}-{uuid.uuid4().hex[:12]}"


def save(df: DataFrame, path: str, kind: str = "parquet") -> None:
    """Text formats keep arrays as JSON strings."""
    if kind == "csv":
        df = df.select(*[F.to_json(c).alias(c) if t.startswith("array") else F.col(c) for c, t in df.dtypes])
    df.write.format(kind).option("header", True).save(path)


def read(spark: SparkSession, path: str, schema: str, kind: str = "parquet") -> DataFrame:
    """Read with the schema given, never an inferred one."""
    if kind != "csv":
        return spark.read.schema(schema).format(kind).load(path)
    wanted = spark.createDataFrame([], schema).schema
    flat = ", ".join(f"{f.name} {'string' if f.dataType.typeName() == 'array' else f.dataType.simpleString()}" for f in wanted)
    raw = spark.read.schema(flat).option("header", True).csv(path)
    return raw.select(*[F.from_json(f.name, f.dataType.simpleString()).alias(f.name) if f.dataType.typeName() == "array" else F.col(f.name) for f in wanted])


class _Steps(InputPartition):
    def __init__(self, t: int) -> None:
        self.t = t


class StaircaseReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.h, self.m, self.seed = (int(options[k]) for k in ("h", "m", "seed"))

    def partitions(self) -> list[_Steps]:
        return [_Steps(t) for t in range(self.h)]

    def read(self, partition: _Steps) -> Iterator[tuple]:
        from overlapix.operators.schemes import pad_hashes

        low = None
        for n, v in enumerate(pad_hashes(self.m, H.draws(self.h, self.seed)[partition.t], "poly", H.PAD_A).tolist(), 1):
            if low is None or v < low:
                low = v
                yield partition.t, n, v


class StaircaseSource(DataSource):
    """``spark.read.format("pad_staircase").option("h", ..).option("m", ..).option("seed", ..)``: a partition a hash."""

    @classmethod
    def name(cls) -> str:
        return "pad_staircase"

    def schema(self) -> str:
        return "t int, m_from bigint, pad_min bigint"

    def reader(self, schema) -> StaircaseReader:
        return StaircaseReader(self.options)
