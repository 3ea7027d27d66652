"""What the corpus operators share: shared storage, tables, word kernels, Arrow helpers."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: The bytes that one word pattern keeps (digits, a-z, all bytes of non-ASCII code points).
_ALNUM = bytes(b if 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80 else 0x20 for b in range(256))
#: Bytes of one Arrow batch on its way to Python.
BATCH_BYTES = 8 << 20
#: Fixed value: the white space of ``[\x20\x09-\x0D]``.
BLANKS = b" \t\n\x0b\x0c\r"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. Where that is unset and everything runs on one
    machine, a local folder; a cluster without a shared folder is an error, since executors don't see the driver's disk."""
    known = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if known:
        return known.rstrip("/")
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="semrank-"))
    return spark.sparkContext._jsc.sc().getCheckpointDir().get().rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    """A path below the shared folder that nobody has used."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Writes ``df`` to the shared folder and reads it back: the lineage ends there, and a lost executor costs nothing."""
    path = new_path(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def file_system(path: str):
    """A pyarrow file system and the path in it; works for file://, hdfs://, s3:// and the like."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path else "file://" + path.removeprefix("file:"))


def alnum_words(text: bytes | None) -> list[bytes]:
    """Words ``[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+`` of the text after A-Z became a-z, as UTF-8 bytes."""
    return text.lower().translate(_ALNUM).split() if text else []


def blank_words(text: bytes | None) -> list[bytes]:
    """Words ``[^\\x20\\x09-\\x0D]+`` after A-Z became a-z, as UTF-8 bytes (bytes.split cuts at exactly these)."""
    return text.lower().split() if text else []


def as_bytes(batch: pa.RecordBatch, name: str = "text") -> list[bytes | None]:
    """A string column as UTF-8 bytes; nulls stay None."""
    column = batch.column(batch.schema.get_field_index(name))
    if pa.types.is_string(column.type):
        column = column.cast(pa.binary())
    elif pa.types.is_large_string(column.type):
        column = column.cast(pa.large_binary())
    return column.to_pylist()


_owner: list = ["", lambda: None]


def enter(name: str, forget: Callable[[], object] = lambda: None) -> None:
    """A Python worker starts a task of an operator: what it remembered for another one goes, back to the system."""
    if _owner[0] != name:
        _owner[1]()
        _owner[:] = [name, forget]
        gc.collect()
        with contextlib.suppress(OSError, AttributeError):  # glibc only
            ctypes.CDLL(None).malloc_trim(0)


def bounded_batches(spark: SparkSession, most: int = BATCH_BYTES) -> None:
    """Arrow batches of few megabytes, whatever the length of texts, so that Python workers need little memory."""
    now = spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None)
    if not now or not now.rstrip("bB").isdigit() or int(now.rstrip("bB")) > most:
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(most))


def per_batch(df: DataFrame, make: Callable[[pa.RecordBatch], dict], schema: str) -> DataFrame:
    """mapInArrow with a function that turns a batch into a dict of columns in the order of ``schema``."""
    types = pa_schema(schema)
    bounded_batches(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_pydict(make(batch), schema=types)

    return df.mapInArrow(run, schema)


def pa_schema(schema: str) -> pa.Schema:
    """The Arrow schema of a DDL string over the simple types used here."""
    simple = {"bigint": pa.int64(), "long": pa.int64(), "int": pa.int32(), "string": pa.string(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_(), "float": pa.float32()}
    fields = []
    for part in schema.split(", "):
        name, kind = part.split(" ")
        fields.append(pa.field(name, pa.list_(simple[kind[6:-1]]) if kind.startswith("array<") else simple[kind]))
    return pa.schema(fields)


def only(df: DataFrame, *names: str) -> DataFrame:
    """The named columns, with a defined type each, whatever else the table has. Ids are whole numbers; a text that spells none stops the job."""
    kinds = {"text": T.StringType(), "doc_id": T.LongType(), "page_id": T.LongType(), "html": T.StringType()}
    return df.select(*(df[n].cast(kinds[n]).alias(n) if n in kinds else df[n] for n in names))
