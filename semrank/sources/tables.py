"""Input tables, payloads, and where intermediate results are kept."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, names=NAMES) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)


def work_path(spark: SparkSession, name: str) -> str:
    """A new path in the folder that driver and executors share (spark.checkpoint.dir). Where that is unset and everything runs on
    one machine, in a local one; a cluster without a shared folder is an error, since executors don't see the driver's disk."""
    known = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not known:
        if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
            if spark.sparkContext.master.split("[")[0] != "local":
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="semrank-"))
        known = spark.sparkContext._jsc.sc().getCheckpointDir().get()
    return f"{known.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def bound_batches(spark: SparkSession, most: int = 8 << 20) -> None:
    """Arrow batches of few megabytes, whatever the length of texts, so that Python workers need little memory."""
    now = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None)
    if not now or not now.rstrip("bB").isdigit() or int(now.rstrip("bB")) > most:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(most))


def materialise(df: DataFrame, name: str = "step") -> DataFrame:
    """Written once and read back, so that ranker calls below it are made once whatever reads the result, and lineage ends."""
    path = work_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def payload_of(schema: T.StructType, names: list[str]) -> Column:
    """Any columns as one text: nested values as JSON, decimals plainly, timestamps in ISO form, null as nothing."""
    parts = []
    for n in names:
        kind = schema[n].dataType
        if isinstance(kind, (T.ArrayType, T.MapType, T.StructType)):
            c = F.to_json(F.col(n))
        elif isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
            c = F.date_format(F.col(n), "yyyy-MM-dd'T'HH:mm:ss")
        else:
            c = F.col(n).cast("string")
        parts.append(F.coalesce(c, F.lit("")))
    return F.concat_ws(" ", *parts)


def items_of(df: DataFrame, id_col: str, score: Column | None = None, payload: Column | None = None, proxy: Column | None = None, scope: Column | None = None) -> DataFrame:
    """The internal items table: only id, payload and scores travel through ranking."""
    none = F.lit(None)
    return df.select(
        (F.lit(0) if scope is None else scope).cast("long").alias("scope"),
        F.col(id_col).cast("long").alias("id"),
        (none if payload is None else payload).cast("string").alias("payload"),
        (none if score is None else score).cast("double").alias("score"),
        (none if proxy is None else proxy).cast("double").alias("proxy"),
    )


def assert_unique_id(items: DataFrame) -> None:
    """Ids must be unique in their scope and not null."""
    bad = items.groupBy("scope", "id").count().filter("count > 1 or id is null").limit(1).collect()
    if bad:
        raise ValueError(f"id {bad[0]['id']} of scope {bad[0]['scope']} is null or occurs {bad[0]['count']} times")


def html_text(html: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags go, five entities are read, white space is one blank."""
    x = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</\1>", " ")
    x = F.regexp_replace(F.regexp_replace(x, r"(?s)<!--.*?-->", " "), r"<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        x = F.replace(x, F.lit(name), F.lit(char))
    return F.trim(F.regexp_replace(x, r"\s+", " "))


def write_ledger(calls: DataFrame, path: str) -> None:
    calls.write.mode("append").partitionBy("algo", "run_id").parquet(path)
