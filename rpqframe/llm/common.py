"""Shared helpers: input normalisation, bounded slicing of Arrow batches, lineage cuts."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker holds as Python objects at one time.
SLICE_BYTES = 4 << 20

#: Maps ASCII other than digits and letters to spaces; used after bytes.lower().
_NOT_WORD = bytes(
    c if c >= 0x80 or 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A else 0x20 for c in range(256)
)


def ascii_words(raw: bytes) -> list[bytes]:
    """Lower-cased A-Z, then runs of ASCII letters, digits and any non-ASCII character."""
    return raw.lower().translate(_NOT_WORD).split()


def text_slices(batch: pa.RecordBatch, column: str = "text", limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, list]]:
    """Cut a batch into row ranges of at most ``limit`` bytes of text (one row at least).

    Yields each range with its texts as bytes; null texts are None.
    """
    col = batch.column(batch.schema.get_field_index(column)).cast(pa.binary())
    at, n = 0, batch.num_rows
    while at < n:
        end, size = at, 0
        while end < n and (end == at or size < limit):
            size += len(col[end].as_buffer() or b"") if col[end].is_valid else 0
            end += 1
        yield batch.slice(at, end - at), col.slice(at, end - at).to_pylist()
        at = end


def pick(df: DataFrame, *names: str) -> DataFrame:
    """Only the named columns; extra columns cannot clash with internal ones afterwards."""
    return df.select(*[F.col(f"`{n}`") for n in names])


def fresh(name: str, *frames: DataFrame) -> str:
    """A column name that none of the frames has, whatever its case."""
    taken = {c.lower() for df in frames for c in df.columns}
    while f"_{name}".lower() in taken:
        name += "_"
    return f"_{name}"


def join_dealt(rows: DataFrame, keys: DataFrame, on: list[str], count: str, total: int) -> DataFrame:
    """Inner join of many rows with a table of one row per key, whose column ``count`` says how many rows the key has.

    A key with more than a share of the ``total`` rows is dealt out over several tasks. There are at most
    four such keys a partition, whatever the size, so these few are broadcast.
    """
    share = max(1, total // (4 * int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    salt, parts = fresh("salt", rows, keys), fresh("parts", rows, keys)
    dealt = keys.withColumn(parts, F.ceil(F.col(count) / share).cast("int"))
    hot = dealt.where(F.col(parts) > 1).select(*on, parts)
    own = rows.join(F.broadcast(hot), on, "left").withColumn(salt, F.when(F.col(parts).isNotNull(), F.pmod(F.xxhash64(*[F.col(f"`{c}`") for c in rows.columns]), F.col(parts))).otherwise(0).cast("int")).drop(parts)
    every = dealt.withColumn(salt, F.explode(F.sequence(F.lit(0), F.greatest(F.col(parts), F.lit(1)) - 1))).drop(parts)
    return own.join(every, [*on, salt]).drop(salt)


_MADE: dict[str, SparkSession] = {}


def checkpoint(df: DataFrame) -> DataFrame:
    """Cut lineage: the rows as a table in the shared folder, whose size decides later joins."""
    spark = df.sparkSession
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/table-{uuid.uuid4().hex}"
    _MADE[path] = spark
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


@atexit.register
def release() -> None:
    """Delete all tables that this process cut lineage with; frames that read them are invalid afterwards."""
    for path, spark in list(_MADE.items()):
        try:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
            del _MADE[path]
        except Exception:  # the session may have ended before
            return


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The folder that the session names; only local mode takes one of its own, as executors elsewhere could not read it."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", "") or sc.getConf().get("spark.checkpoint.dir", "")
        if not named and not re.match(r"local(\[|$)", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="rpqframe-checkpoint-"))


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
