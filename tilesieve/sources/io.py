"""Tables with explicit schemas, text and generic sources, and filters on disk."""

from __future__ import annotations

import json
import tempfile
import uuid
from contextlib import contextmanager
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tilesieve.functions.sizing import FilterSpec
from tilesieve.operators.bloom import Filter, pack

SCHEMAS = {
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "benchmark": "item_id bigint, text string",
    "pages": "page_id bigint, url string, html string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
    "labels": "doc_id bigint, quality int, toxic int",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
}

TEXT_TABLES = ("documents", "pages", "conversations")


def scratch_root(spark: SparkSession) -> str:
    """The folder that driver and executors share, as ``spark.checkpoint.dir`` names it.

    Only a local session, whose tasks are one machine's, may do without; a cluster that names none is an error.
    """
    if root := spark.conf.get("spark.checkpoint.dir", None):
        return root.rstrip("/")
    if spark.sparkContext.master.split("[")[0] != "local":
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return f"file://{tempfile.gettempdir()}/tilesieve-scratch"


BATCH, BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 4 << 20


@contextmanager
def small_batches(spark: SparkSession, wanted: bool = True):
    """Tasks of jobs in here exchange rows with Python by a few MB."""
    before = spark.conf.get(BATCH, None)
    if wanted:
        spark.conf.set(BATCH, str(BATCH_BYTES))
    try:
        yield
    finally:
        if wanted:
            spark.conf.unset(BATCH) if before is None else spark.conf.set(BATCH, before)


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df``, written to the shared folder and read from there: made once, however often it is read."""
    path = f"{scratch_root(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; text tables are read with their schema, and only the columns used are read at all.

    A text table in fewer parts than there are cores, such as one file of one row group, is dealt to
    all of them: grams cost far more than the move. Large tables have parts enough and stay as they are.
    """
    reader = spark.read.schema(SCHEMAS[name]) if name in SCHEMAS else spark.read
    table = reader.parquet(f"{sf_dir}/{name}.parquet")
    cores = spark.sparkContext.defaultParallelism
    return table.repartition(cores) if name in TEXT_TABLES and table.rdd.getNumPartitions() < cores else table


def load_lines(spark: SparkSession, path: str, *, whole: bool = False) -> DataFrame:
    """Text files as lines, or as one row a file."""
    return spark.read.text(path, wholetext=whole)


def load_any(spark: SparkSession, path: str, fmt: str, schema: str) -> DataFrame:
    reader = spark.read.format(fmt).schema(schema)
    return (reader.option("header", True) if fmt == "csv" else reader).load(path)


def inline(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def save_filter(filter_: Filter, path: str, *, mode: str = "errorifexists") -> None:
    """Bitmaps sorted by bucket, and the spec beside them."""
    filter_.table.sortWithinPartitions("bucket").write.mode(mode).parquet(f"{path}/bits")
    spec = filter_.table.sparkSession.createDataFrame([(json.dumps(asdict(filter_.spec)),)], "spec string")
    spec.coalesce(1).write.mode(mode).text(f"{path}/spec")


def load_filter(spark: SparkSession, path: str, expect: FilterSpec | None = None) -> Filter:
    """A stored filter; refuses one of another geometry than ``expect``."""
    spec = FilterSpec(**json.loads(spark.read.text(f"{path}/spec").first()[0]))
    if expect is not None:
        spec.require(expect)
    return Filter(spec, spark.read.schema("bucket bigint, bitmap binary").parquet(f"{path}/bits"))


def save_packed(filter_: Filter, path: str) -> None:
    """One local file to hand out: a line of spec, then the bits."""
    with open(path, "wb") as f:
        f.write(json.dumps(asdict(filter_.spec)).encode() + b"\n" + pack(filter_))


def load_packed(path: str) -> tuple[FilterSpec, bytes]:
    with open(path, "rb") as f:
        return FilterSpec(**json.loads(f.readline())), f.read()


def rejoin_lines(df: DataFrame, *, key: str, order: str, text: str = "text", separator: str = " ") -> DataFrame:
    """(key, text): documents rebuilt from their lines in order."""
    lines = F.array_sort(F.collect_list(F.struct(order, text)))
    return df.groupBy(key).agg(lines.alias("l")).select(key, F.array_join(F.transform("l", lambda x: x[text]), separator).alias("text"))
