"""Session helpers: table access, shared scratch tables that cut lineage, size-checked broadcasts."""

from __future__ import annotations

import atexit
import functools
import os
import pickle
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable
from typing import Any

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BinaryType, DataType, MapType, StringType, StructType

#: A side is broadcast only if it is written in at most so many bytes, and takes at most so many in memory; beyond that, joins shuffle.
BROADCAST_BYTES, BROADCAST_MEMORY = 24 << 20, 128 << 20
#: Bytes of a row and of a cell in memory, beside text, bytes and the elements of arrays.
ROW_BYTES, CELL_BYTES = 32, 8


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given parquet tables, through Spark's own reader, so any file system works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@functools.cache
def _own_dir() -> str:
    """A folder of this process, removed when it ends."""
    os.makedirs(f"{tempfile.gettempdir()}/checkpoints", exist_ok=True)
    path = tempfile.mkdtemp(prefix="tilestar-", dir=f"{tempfile.gettempdir()}/checkpoints")
    atexit.register(shutil.rmtree, path, ignore_errors=True)
    return f"file://{path}"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of our own where it is unset."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
        return _own_dir()
    house = spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
    if house.startswith(("file:", "/")):
        raise ValueError("machines do not share a local warehouse folder: set spark.checkpoint.dir to a folder that all of them reach")
    return f"{house}/_scratch"


class Scratch:
    """Written intermediate tables. A written table survives the loss of executors and ends the lineage."""

    def __init__(self, spark: SparkSession, label: str) -> None:
        self.spark, self.base = spark, f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"

    def _fs(self, name: str):
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(f"{self.base}/{name}")
        return path, path.getFileSystem(self.spark._jsparkSession.sessionState().newHadoopConf())

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.mode("overwrite").option("compression", "zstd").parquet(f"{self.base}/{name}")
        return self.spark.read.schema(df.schema).parquet(f"{self.base}/{name}")

    def size(self, name: str) -> int:
        path, fs = self._fs(name)
        return fs.getContentSummary(path).getLength()

    def drop(self, *names: str) -> None:
        for name in names:
            path, fs = self._fs(name)
            fs.delete(path, True)

    def small(self, df: DataFrame, name: str) -> DataFrame:
        """df, read from table `name`, marked for broadcast if it is small, as written and in memory."""
        return F.broadcast(df) if self.size(name) <= BROADCAST_BYTES and in_memory(df) <= BROADCAST_MEMORY else df


def bucketed(df: DataFrame, keys: list[str], buckets: int) -> DataFrame:
    """df, stored in shared scratch storage in sorted buckets of its keys: joins and sums on them move nothing. The table's name lasts as long as the session's catalog."""
    scratch, name = Scratch(df.sparkSession, "bucketed"), f"bucketed_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, *keys).sortBy(*keys).option("path", f"{scratch.base}/{name}").format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)


def _cell(value: Column, kind: DataType) -> Column:
    """Bytes of a value in a row of Spark's own format."""
    if isinstance(kind, (StringType, BinaryType)):
        return F.lit(CELL_BYTES) + F.coalesce(F.octet_length(value), F.lit(0))
    if isinstance(kind, StructType):
        return functools.reduce(lambda a, f: a + _cell(value[f.name], f.dataType), kind.fields, F.lit(CELL_BYTES))
    if isinstance(kind, ArrayType):
        return F.aggregate(F.coalesce(value, F.array().cast(kind)), F.lit(3 * CELL_BYTES).cast("bigint"), lambda n, x: n + _cell(x, kind.elementType).cast("bigint"))
    if isinstance(kind, MapType):
        return _cell(F.map_keys(value), ArrayType(kind.keyType)) + _cell(F.map_values(value), ArrayType(kind.valueType))
    return F.lit(CELL_BYTES)


def in_memory(df: DataFrame) -> int:
    """Bytes of df's rows in memory, counted in one pass over a written table that is small on disk."""
    each = functools.reduce(lambda a, f: a + _cell(F.col(f"`{f.name}`"), f.dataType), df.schema.fields, F.lit(ROW_BYTES))
    return df.agg(F.sum(each.cast("bigint"))).first()[0] or 0


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value evaluated once a row, however often and however deep body uses it."""
    return F.transform(F.array(value), body)[0]


def kept_in_workers(spark: SparkSession, value: Any) -> Callable[[], Any]:
    """A function for use in tasks that gives `value`, a bounded object, which a Python worker unpacks once and keeps from task to task."""
    sent = spark.sparkContext.broadcast({"packed": cloudpickle.dumps(value)})

    def get() -> Any:
        box = sent.value
        if "value" not in box:
            box["value"] = pickle.loads(box["packed"])
        return box["value"]

    return get
