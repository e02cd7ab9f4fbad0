"""Document fingerprints: every shingle hash below a fixed fraction of the hash space is kept."""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mix64, texts_of, window_hashes

#: Code points of a shingle, the kept share of the hash space (one in SCALE), and the hashes kept at least.
SHINGLE = 16
SCALE = 32
AT_LEAST = 32


def sketch(text: str, shingle: int = SHINGLE, scale: int = SCALE, at_least: int = AT_LEAST) -> np.ndarray:
    """Sorted 32-bit hashes of the shingles below 2^32/scale, and in any case the at_least smallest.

    The kept set depends on the set of shingles alone; sketches of parts merge into that of the whole by merge().
    A text shorter than a shingle is one shingle; the empty text has none.
    """
    if not text:
        return np.empty(0, np.uint32)
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    h = window_hashes(mix64(points + np.uint64(1)), min(shingle, len(points)))
    h = (h >> np.uint64(32)).astype(np.uint32)
    low = np.unique(h[h < np.uint32(0xFFFFFFFF // scale)])
    if len(low) < at_least:
        low = np.unique(h)[:at_least]
    return low


def merge(a: np.ndarray, b: np.ndarray, scale: int = SCALE, at_least: int = AT_LEAST) -> np.ndarray:
    """Sketch of the union of two shingle sets."""
    both = np.union1d(a, b)
    low = both[both < np.uint32(0xFFFFFFFF // scale)]
    return low if len(low) >= at_least else both[:at_least]


def encode(s: np.ndarray) -> str:
    return base64.b64encode(s.astype("<u4").tobytes()).decode()


def decode(text: str) -> np.ndarray:
    return np.frombuffer(base64.b64decode(text), "<u4")


def shared(a: np.ndarray, b: np.ndarray) -> tuple[int, int, int]:
    """Hashes in both, in a and in b, counted below the bound up to which both sketches are complete."""
    bound = lambda s: max(int(s[-1]) if len(s) <= AT_LEAST and len(s) else 0, 0xFFFFFFFF // SCALE - 1) if len(s) >= AT_LEAST else 0xFFFFFFFF
    top = np.uint32(min(bound(a), bound(b)))
    a, b = a[a <= top], b[b <= top]
    return len(np.intersect1d(a, b, assume_unique=True)), len(a), len(b)


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Estimated share of the smaller shingle set that lies in the larger one; 1 for two empty sets, 0 for one."""
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    both, in_a, in_b = shared(a, b)
    return both / min(in_a, in_b) if min(in_a, in_b) else 0.0


#: Ids of least hash for each range from which bounds of text ids are taken.
_DRAWN = 64


def next_ranges(docs: DataFrame, n: int) -> tuple[list, tuple | None]:
    """Up to n - 1 ids that occur in docs and part them about evenly; the least and greatest id.

    Numbers by approximate percentiles, text by the order of the _DRAWN * n ids of least hash. Bounds only deal rows out.
    """
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()
    ends = docs.agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")).first()
    if ends["lo"] is None:
        return [], None
    if kind == "string":
        drawn = docs.select("doc_id").where(F.col("doc_id").isNotNull()).orderBy(F.xxhash64("doc_id"), "doc_id").limit(_DRAWN * n).collect()
        ids = sorted({r["doc_id"] for r in drawn})
        return sorted({ids[len(ids) * k // n] for k in range(1, n)}), (ends["lo"], ends["hi"])
    q = docs.agg(F.percentile_approx("doc_id", [i / n for i in range(1, n)] or [0.5], 10_000).alias("q")).first()["q"]
    return sorted(set(q or [])), (ends["lo"], ends["hi"])


def fingerprints(docs: DataFrame, partitions: int | None = None) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness; one row for each row of docs.

    The next document is that of the next smaller doc_id, after the last the one of the greatest. Documents are
    dealt once, by ranges of doc_id whose bounds are ids of documents; a bound's document also goes to the range
    above it, which needs its text as the next one, and the greatest to the lowest range. Rows with null text count
    as empty, rows of equal id are ordered by text, rows with a null id come after all others and have the next
    row of their own range or else the greatest id's as next. No rows give no rows; a single row is its own next.
    """
    n = partitions or int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    bounds, ends = next_ranges(docs, n)
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()
    marks, greatest = bounds, ends and ends[1]

    @F.pandas_udf("array<int>")
    def ranges(ids):
        # (bounds[k-1], bounds[k]] is range k; a bound, and the greatest id for range 0, also serve the range above.
        import bisect

        import pandas as pd

        def of(i):
            if i is None or i != i:
                return [0]
            k = bisect.bisect_left(marks, i)
            out = [k, -k - 2] if k < len(marks) and marks[k] == i else [k]
            return [*out, -1] if i == greatest else out

        return pd.Series([of(i) for i in ids.tolist()])

    def run(batches):
        held = None  # the row that waits for its next: (own, id, text, sketch)
        first = []
        rows: list = []

        def flush():
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 7
            rows.clear()
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=names)

        for batch in batches:
            for own, i, t in zip(batch.column("own").to_pylist(), batch.column("doc_id").to_pylist(), texts_of(batch), strict=True):
                s = sketch(t)
                if not first:
                    first.append((t, s))
                if held is not None and held[0]:
                    rows.append(finish(held, t, s))
                    if len(rows) >= 2000:
                        yield flush()
                if held is None or held[0] or own:
                    held = (own, i, t, s)
        if held is not None and held[0]:
            rows.append(finish(held, *first[0]))
        if rows:
            yield flush()

    def finish(held, t, s):
        _, i, own_text, own = held
        half = len(own_text) // 2
        edited = own_text[: len(own_text) - half] + t[:half]
        e = sketch(edited)
        sha = hashlib.sha256(edited.encode("utf-8", "surrogatepass")).hexdigest()
        return i, len(own_text), sha, encode(own), encode(e), likeness(own, e), likeness(own, s)

    id_type = {"string": pa.string(), "bigint": pa.int64()}.get(kind, pa.int32())
    types = [id_type, pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    known = F.coalesce("doc_id", F.lit(ends[0] if ends else None).cast(kind))  # no nulls, which would make numbers inexact
    part = F.explode(F.when(F.col("doc_id").isNull(), F.array(F.lit(0))).otherwise(ranges(known))).alias("r")
    dealt = docs.select("doc_id", "text", part)
    # Helpers: -1 is the greatest id for the lowest range, -k-2 the bound above range k for range k + 1.
    at = F.when(F.col("r") >= 0, F.col("r")).when(F.col("r") == -1, 0).otherwise(-F.col("r") - 1)
    dealt = dealt.select("doc_id", "text", at.alias("at"), (F.col("r") >= 0).alias("own"), (F.col("r") == -1).cast("int").alias("last"))
    dealt = dealt.repartitionById(len(bounds) + 1, F.col("at")).sortWithinPartitions("last", F.col("doc_id").desc_nulls_last(), F.col("own").desc(), "text")
    return dealt.mapInArrow(run, f"doc_id {kind}, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


#: The fixed columns of fingerprints() in DuckDB, over the view documents.
EDITS_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
n AS (SELECT doc_id, t, coalesce(lead(t) OVER (ORDER BY doc_id DESC), first_value(t) OVER (ORDER BY doc_id DESC)) AS after FROM d)
SELECT doc_id, length(t)::BIGINT AS n_chars, sha256(substring(t, 1, length(t) - length(t) // 2) || substring(after, 1, length(t) // 2)) AS edited_sha256 FROM n
"""
