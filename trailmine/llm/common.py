"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: White space of the contracts: space and the control characters tab to carriage return.
SPACES = r"[\x20\x09-\x0D]+"


_BASES: dict[str, str] = {}


def scratch_dir(spark: SparkSession) -> str:
    """A fresh folder under ``spark.checkpoint.dir``, which driver and executors share. All of a
    session's folders are removed when the driver's JVM ends.

    Only a local session without that setting falls back to a folder of its own.
    """
    app = spark.sparkContext.applicationId
    if app not in _BASES:
        base = spark.conf.get("spark.checkpoint.dir", None)
        if not base:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            base = "file:///tmp/checkpoints"
        own = f"{base.rstrip('/')}/trailmine-{uuid.uuid4().hex}"
        path = spark._jvm.org.apache.hadoop.fs.Path(own)
        store = path.getFileSystem(spark._jsc.hadoopConfiguration())
        store.mkdirs(path)
        store.deleteOnExit(path)
        _BASES[app] = own
    return f"{_BASES[app]}/{uuid.uuid4().hex}"


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back: lineage ends here,
    and a lost executor costs no recomputation of what stands above."""
    spark = df.sparkSession
    path = f"{scratch_dir(spark)}/{name}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bound_batches(spark: SparkSession, rows: int = 2000, mb: int = 32) -> None:
    """Bound the Arrow batches by rows and bytes, so that a Python worker's memory does not
    follow the length of texts. Both are runtime settings; stricter ones stay."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key, "10000"))
    if now <= 0 or now > rows:
        spark.conf.set(key, str(rows))
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(mb << 20))


def trimmed(run):
    """``run``, a function over batches, after which its worker gives back the memory that is free:
    idle workers stay beside the next stage's tasks, and their allocators keep what they have had."""

    def wrapped(batches):
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
            trim(0)

    return wrapped


def whole_text(text: Column | str = "text") -> Column:
    """The text, null as empty."""
    return F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit(""))


def whole_row(docs: DataFrame) -> Column:
    """All columns as one struct, so that no name of an operator's own can clash with them."""
    return F.struct(*[F.col(f"`{c}`") for c in docs.columns])


def fence(df: DataFrame) -> DataFrame:
    """``df``, whose columns a filter above is not rewritten into: it would compute them again,
    and those that stand inside a function over an array once for each element."""
    return df.select(F.inline(F.array(F.struct(*df.columns))))


def find_last(values: Column, key: Column, most: int) -> Column:
    """Index of the last of the sorted ``values``, at most ``most``, that is not above ``key``; -1
    if there is none. By bisection, inside the row."""
    steps = F.array(*[F.lit(1 << k) for k in reversed(range(max(1, most.bit_length())))])
    return F.aggregate(steps, F.lit(-1), lambda at, step: F.when(F.get(values, at + step) <= key, at + step).otherwise(at))


def text_digest(text: Column | str = "text") -> Column:
    """16 bytes that, with the id, tell rows apart that share an id or have none."""
    return F.unhex(F.md5(whole_text(text).cast("binary")))


def words(text: Column | str = "text") -> Column:
    """Words of a text: runs of anything but the contract's white space."""
    return F.array_remove(F.split(whole_text(text), SPACES), "")


def id_crc(doc_id: str = "doc_id") -> Column:
    """crc32 of the id written as text; a null id counts as empty text."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")
