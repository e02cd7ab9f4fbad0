"""Helpers shared by the corpus operators: scratch tables, words, shingles, Arrow maps."""

from __future__ import annotations

import atexit
import ctypes
import os
import tempfile
import uuid
import zlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_VOCAB_LIMIT = 400_000
#: Scratch folders made so far and not removed.
_SCRATCH: list[str] = []


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where none is named."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    path = os.path.join(tempfile.gettempdir(), "mjoin-scratch")
    os.makedirs(path, exist_ok=True)
    return f"file://{path}"


def scratch_path(spark: SparkSession, label: str) -> str:
    """A fresh folder name under the shared folder, deleted when the driver ends."""
    path = f"{shared_dir(spark)}/mjoin-{label}-{uuid.uuid4().hex[:12]}"
    atexit.register(_remove, spark, path)
    _SCRATCH.append(path)
    return path


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
    except Exception:  # the session may have ended; the folder is scratch space
        pass


def settle(df: DataFrame, label: str) -> DataFrame:
    """Write df once to the shared folder and read it back: cuts lineage and survives lost executors."""
    path = scratch_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def settle_alone(spark: SparkSession, build, label: str) -> DataFrame:
    """build() settled; the scratch tables made by building it go, as the result is read from its own."""
    begin = len(_SCRATCH)
    df = build()
    end = len(_SCRATCH)
    out = settle(df, label)
    for path in _SCRATCH[begin:end]:
        _remove(spark, path)
    del _SCRATCH[begin:end]
    return out


def release_memory() -> None:
    """Give memory that nothing uses any more back to the system: Python workers go on to later stages with what they have."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not every C library has it
        pass


def map_arrow(df: DataFrame, fn, schema: str) -> DataFrame:
    """mapInArrow where fn turns one RecordBatch into a dict of columns; schema is a DDL string."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    out = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                cols = fn(batch)
                yield pa.RecordBatch.from_arrays([as_arrow(cols[f.name], f.type) for f in out], schema=out)
                del cols
        release_memory()

    return df.mapInArrow(run, schema)


def as_arrow(values, kind: pa.DataType) -> pa.Array:
    if isinstance(values, pa.Array):
        return values if values.type == kind else values.cast(kind)
    return pa.array(values, type=kind)


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    """Texts of a batch, null as the empty text."""
    return [t or "" for t in batch.column(name).to_pylist()]


def held_out(column) -> F.Column:
    """True where crc32 of the id's text leaves no remainder by 5: never trained on."""
    return F.crc32(F.coalesce(column.cast("string"), F.lit("")).cast("binary")) % 5 == 0


def crc_of(value) -> int:
    return zlib.crc32(b"" if value is None else str(value).encode())


def words_of(text: str) -> list[bytes]:
    """Maximal runs of anything but tab to carriage return and space, as UTF-8.

    bytes.split() parts at exactly these six characters, unlike str.split(), which also parts at other Unicode spaces.
    """
    return text.encode("utf-8", "surrogatepass").split()


class WordHashes:
    """64-bit hashes of words, remembered for frequent words within a bounded table."""

    def __init__(self, seed: int = 0):
        self.seed, self.known = seed, {}

    def __call__(self, words: list[bytes]) -> np.ndarray:
        known, seed = self.known, self.seed
        if len(known) > _VOCAB_LIMIT:
            known.clear()
        for w in set(words).difference(known):
            known[w] = xxhash.xxh64_intdigest(w, seed)
        return np.fromiter(map(known.__getitem__, words), np.uint64, len(words))


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser, so that low and high bits both look random."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def window_hashes(h: np.ndarray, width: int, base: int = 0x9E3779B97F4A7C15) -> np.ndarray:
    """Polynomial hash of every run of width symbols, by doubling; empty where there are fewer."""
    n = len(h) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    b = base & 0xFFFFFFFFFFFFFFFF
    total, done, part, size = None, 0, h, 1
    power = b
    rest = width
    while rest:
        if rest & 1:
            piece = part[done : done + n]
            if total is None:
                total = piece.copy()
            else:
                total = total * np.uint64(pow(b, size, 1 << 64)) + piece
            done += size
        rest >>= 1
        if rest:
            m = len(part) - size
            part = part[:m] * np.uint64(power) + part[size : size + m]
            power = power * power & 0xFFFFFFFFFFFFFFFF
            size *= 2
    return mix64(total)
