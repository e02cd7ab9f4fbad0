"""Substring dedup: recurring passages are confirmed in the texts in which they first stand, compiled into sharded Aho-Corasick automata, and located by streaming the documents through them."""

from __future__ import annotations

import hashlib

import ahocorasick
import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from .common import WordHashes, map_arrow, mix64, settle, texts_of, window_hashes, words_of

#: Words of a window; words of passages in one shard; bytes of texts that one task streams through a shard.
WINDOW = 50
SHARD_WORDS = 1_000_000
UNIT_BYTES = 48 << 20
_SECOND_BASE = 0xC2B2AE3D27D4EB4F
#: A word of a seed is three letters, each of an alphabet of its own of so many: nodes of the automata then have few edges,
#: which are searched one by one, and no match begins inside a word. Letters of no word.
_LETTERS, _NO_WORD = 128, "\0\0\0"
_POINTS = _LETTERS**3
#: Places in the passages of a shard up to which a seed is rare.
_RARE = 2


def _sliding(x: np.ndarray, width: int, fold) -> np.ndarray:
    """fold (minimum or maximum) of every run of width values, by doubling."""
    size = 1
    out = x
    while size * 2 <= width:
        out = fold(out[: len(out) - size], out[size:])
        size *= 2
    rest = width - size
    return fold(out[: len(x) - width + 1], out[rest : rest + len(x) - width + 1])


def shingle_width(window: int) -> int:
    return (window + 1) // 2


def window_anchors(h: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Shingle hashes, and for each window the least of the shingles inside it: its anchor.

    Equal windows have equal anchors, so a window can recur only where its anchor does.
    """
    g = window_hashes(h, shingle_width(window))
    return g, _sliding(g, window - shingle_width(window) + 1, np.minimum)


def text_key(words: list[bytes]) -> bytes:
    return xxhash.xxh3_128_digest(b" ".join(words))


def _profile(docs: DataFrame, window: int) -> DataFrame:
    """doc_id, key of the word sequence, n_words, sha256 of all words, and the distinct anchors of each row."""
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def run(batch):
        hashes, cols = WordHashes(), [[] for _ in range(4)]
        for doc, t in zip(batch.column("doc_id").to_pylist(), texts_of(batch), strict=True):
            words = words_of(t)
            joined = b" ".join(words)
            long = len(words) >= window and doc is not None
            row = xxhash.xxh3_128_digest(joined), len(words), hashlib.sha256(joined).hexdigest(), np.unique(window_anchors(hashes(words), window)[1]).view(np.int64) if long else None
            for c, v in zip(cols, row, strict=True):
                c.append(v)
        return {"doc_id": batch.column("doc_id"), "key": cols[0], "n_words": cols[1], "sha": cols[2], "anchors": cols[3]}

    return map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, key binary, n_words bigint, sha string, anchors array<bigint>")


def _windows(candidates: DataFrame, window: int) -> DataFrame:
    """Two hashes, doc_id, text number and position of every window whose anchor is among the row's recurring anchors."""

    def run(batch):
        hashes, out, n = WordHashes(), [[], [], [], []], []
        for own, t, anchors in zip(batch.column("t").to_pylist(), texts_of(batch), batch.column("anchors").to_pylist(), strict=True):
            h = hashes(words_of(t))
            least = window_anchors(h, window)[1]
            at = np.flatnonzero(np.isin(least, np.array(anchors, np.int64).view(np.uint64)))
            out[0].append(window_hashes(h, window)[at].view(np.int64))
            out[1].append(window_hashes(h, window, _SECOND_BASE)[at].view(np.int64))
            out[2].append(np.full(len(at), own, np.int64))
            out[3].append(at.astype(np.int32))
            n.append(len(at))
        cols = {k: np.concatenate(v) for k, v in zip(("w1", "w2", "t", "pos"), out, strict=True)}
        return cols | {"doc_id": batch.column("doc_id").take(pa.array(np.repeat(np.arange(len(n)), n)))}

    kind = next(f.dataType for f in candidates.schema if f.name == "doc_id").simpleString()
    return map_arrow(candidates, run, f"w1 bigint, w2 bigint, doc_id {kind}, t bigint, pos int")


def _passages(firsts: DataFrame, window: int) -> DataFrame:
    """The passages of each row of firsts (doc_id, t, text, at: positions of recurring windows that first stand there).

    A passage is a longest run of such windows: its source, its words (joined by a space), and the anchors of its windows.
    """

    def run(batch):
        hashes, out, n = WordHashes(), [[], [], []], []
        for t, at in zip(texts_of(batch), batch.column("at").to_pylist(), strict=True):
            words, pos = words_of(t), np.unique(np.array(at, np.int64))
            least = window_anchors(hashes(words), window)[1]
            cuts = np.concatenate([[0], np.flatnonzero(np.diff(pos) != 1) + 1, [len(pos)]])
            for a, z in zip(pos[cuts[:-1]], pos[cuts[1:] - 1] + 1, strict=True):
                out[0].append(b" ".join(words[a : z - 1 + window]).decode("utf-8", "surrogatepass"))
                out[1].append(z - 1 + window - a)
                out[2].append(np.unique(least[a:z]).view(np.int64))
            n.append(len(cuts) - 1)
        at = pa.array(np.repeat(np.arange(len(n)), n))
        return {"doc_id": batch.column("doc_id").take(at), "t": batch.column("t").take(at), "text": out[0], "n": out[1], "anchors": pa.array(out[2], pa.list_(pa.int64()))}

    kind = next(f.dataType for f in firsts.schema if f.name == "doc_id").simpleString()
    return map_arrow(firsts, run, f"doc_id {kind}, t bigint, text string, n bigint, anchors array<bigint>")


def seed_layout(window: int) -> tuple[int, int]:
    """Words of a seed, and the number of places in a window at which one can begin."""
    size = max(1, window // 6)
    return size, window - size + 1


class PassageShard:
    """Aho-Corasick automata over seeds of passages; what stands around a found seed is compared word by word.

    Each window of a passage holds a whole seed. Of the word sequences that can be one, the rarest among all passages of the
    shard is taken, so that passages that differ in a few words are told apart by seeds over these. Seeds of more distinct
    words than points go to further automata.
    """

    def __init__(self, passages: list[tuple], window: int, points: int = _POINTS):
        self.window = window
        self.size, gap = seed_layout(window)
        self.numbers: dict[bytes, int] = {}
        number = self.numbers.setdefault
        parts = [np.array([number(w, len(self.numbers) + 1) for w in words], np.int64) for _, words in passages]
        # passages after each other, -1 between them and at both ends
        starts = 1 + np.concatenate([[0], np.cumsum([len(p) + 1 for p in parts])]).astype(np.int64)
        self.flat = np.full(int(starts[-1]), -1, np.int64)
        for first, p in zip(starts, parts, strict=False):
            self.flat[first : first + len(p)] = p
        _, at, often = np.unique(window_hashes(mix64(self.flat.view(np.uint64)), self.size), return_inverse=True, return_counts=True)
        often = often[at]
        seeds: dict[tuple, list[tuple]] = {}
        for first, (source, words) in zip(starts.tolist(), passages, strict=False):
            k, windows = 0, len(words) - window + 1
            while k < windows:
                # a seed that begins at j serves windows k to j: later ones serve more, but the rarest is taken, of the later half if it is rare there
                near = often[first + k : first + k + gap][::-1]
                back = int(near[: gap - gap // 2].argmin())
                if near[back] > _RARE:
                    back = int(near.argmin())
                j = k + gap - 1 - back
                seeds.setdefault(tuple(words[j : j + self.size]), []).append((first + j, source))
                k = j + 1
        self.machines = []
        machine = None
        for words, places in seeds.items():
            if machine is None or len(known) + self.size > points:
                machine, known = ahocorasick.Automaton(), {}
                self.machines.append((machine, known))
            for w in words:
                if w not in known:
                    k = len(known)
                    known[w] = chr(1 + k % _LETTERS) + chr(1 + _LETTERS + k // _LETTERS % _LETTERS) + chr(1 + 2 * _LETTERS + k // _LETTERS**2)
            machine.add_word("".join(map(known.__getitem__, words)), places)
        for machine, _ in self.machines:
            machine.make_automaton()

    def cover(self, words: list[bytes], own) -> list[tuple[int, int]]:
        """(first, after last) of the stretches of a document that stand, at least a window long, in a passage of smaller source."""
        out, numbers, n, size, flat = [], None, len(words), self.size, self.flat
        for machine, known in self.machines:
            get, done, lo, hi = known.get, {}, 0, 0  # lo and hi: the last stretch found
            for letter, places in machine.iter("".join([get(w, _NO_WORD) for w in words])):
                last = letter // 3
                at = last - size + 1
                for place, source in places:
                    if not source < own or at < done.get(place - at, 0):  # this alignment was compared beyond here
                        continue
                    if numbers is None:
                        numbers = np.fromiter((self.numbers.get(w, 0) for w in words), np.int64, n)
                    if lo <= at and last < hi:
                        # a match inside a stretch adds something only if it goes on at one of its ends
                        right, left = place + hi - at, place - (at - lo) - 1
                        if not (hi < n and right < len(flat) and flat[right] == numbers[hi]) and not (lo > 0 and left > 0 and flat[left] == numbers[lo - 1]):
                            continue
                    after = at + _equal(numbers[at:], self.flat[place:])
                    first = at - _equal(numbers[:at][::-1], self.flat[:place][::-1])
                    done[place - at] = after
                    if after - first >= self.window:
                        out.append((first, after))
                        lo, hi = (min(lo, first), max(hi, after)) if first <= hi and lo <= after else (first, after)
        return out


def _equal(a: np.ndarray, b: np.ndarray) -> int:
    """How many leading values agree."""
    n, step, most = 0, 64, min(len(a), len(b))
    while n < most:
        other = np.flatnonzero(a[n : min(n + step, most)] != b[n : min(n + step, most)])
        if len(other):
            return n + int(other[0])
        n, step = n + step, step * 2
    return most


def _locate(passages: DataFrame, candidates: DataFrame, window: int, shard_words: int, unit_bytes: int) -> DataFrame:
    """doc_id, t and spans of the documents in which passages of smaller sources occur.

    Passages are dealt into shards by their source text. A document holds an occurrence only if it has an anchor
    of the passage (each window holds its anchor), so it is streamed through every shard that has one of its anchors.
    A shard's documents are parted into units of about unit_bytes, each of which gets the shard's passages first.
    """
    shards = max(1, -(-(passages.agg(F.sum("n")).first()[0] or 0) // shard_words))
    shard = F.pmod(F.xxhash64("t"), F.lit(shards)).cast("int").alias("shard")
    known = settle(passages.select(F.explode("anchors").alias("anchor"), shard).distinct(), "phrases-passage-anchors")
    routes = candidates.select("doc_id", "t", F.length("text").alias("size"), F.explode("anchors").alias("anchor")).join(known, "anchor")
    routes = settle(routes.select("doc_id", "t", "size", "shard").distinct(), "phrases-routes")
    units = routes.groupBy("shard").agg(F.ceil(F.sum("size") / unit_bytes).cast("int").alias("units"))
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    units = settle(units.withColumn("begin", F.coalesce(F.sum("units").over(before), F.lit(0)).cast("int")), "phrases-units")  # a row for each shard
    n = max(1, units.agg(F.sum("units")).first()[0] or 0)
    first = passages.select(shard, "doc_id", "t", "text").join(units, "shard").withColumn("unit", F.explode(F.sequence(F.col("begin"), F.col("begin") + F.col("units") - 1))).withColumn("side", F.lit(0))
    texts = candidates.select("doc_id", "t", "text").join(routes.drop("size"), ["doc_id", "t"]).join(units, "shard")
    texts = texts.withColumn("unit", F.pmod(F.xxhash64(F.lit("unit"), "doc_id", "t"), F.col("units")).cast("int") + F.col("begin")).withColumn("side", F.lit(1))
    columns = ["unit", "side", "doc_id", "t", "text"]
    both = first.select(*columns).unionByName(texts.select(*columns))
    dealt = both.repartitionById(n, F.col("unit")).sortWithinPartitions("unit", "side", "doc_id", "t")  # a task for each unit
    kind = next(f.dataType for f in candidates.schema if f.name == "doc_id").simpleString()
    schema = f"doc_id {kind}, t bigint, spans array<struct<first:int,after:int>>"
    out = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches):
        own, held, machine = None, [], None
        for batch in batches:
            found = [[], [], []]
            keys = zip(batch.column("unit").to_pylist(), batch.column("side").to_pylist(), strict=True)
            for key, doc, t, text in zip(keys, batch.column("doc_id").to_pylist(), batch.column("t").to_pylist(), texts_of(batch), strict=True):
                if key[0] != own:
                    own, held, machine = key[0], [], None
                if key[1] == 0:
                    held.append((doc, words_of(text)))
                    continue
                if machine is None:
                    machine, held = PassageShard(held, window), []
                if spans := machine.cover(words_of(text), doc):
                    for c, v in zip(found, (doc, t, [{"first": a, "after": z} for a, z in spans]), strict=True):
                        c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(found, out, strict=True)], schema=out)

    return dealt.mapInArrow(run, schema)


def _cut(found: DataFrame) -> DataFrame:
    """doc_id, t, n_removed, sha256 of the kept words and merged spans of rows (doc_id, t, text, spans)."""

    def run(batch):
        out = [[], [], []]
        for t, spans in zip(texts_of(batch), batch.column("spans").to_pylist(), strict=True):
            words = words_of(t)
            edge = np.zeros(len(words) + 1, np.int64)
            np.add.at(edge, [s["first"] for s in spans], 1)
            np.add.at(edge, [s["after"] for s in spans], -1)
            gone = np.cumsum(edge[:-1]) > 0
            turns = np.flatnonzero(np.diff(np.concatenate([[0], gone.astype(np.int8), [0]])))
            out[0].append(int(gone.sum()))
            out[1].append(hashlib.sha256(b" ".join([w for w, g in zip(words, gone, strict=True) if not g])).hexdigest())
            out[2].append([{"first": int(a), "after": int(z)} for a, z in zip(turns[::2], turns[1::2], strict=True)])
        return {"doc_id": batch.column("doc_id"), "t": batch.column("t"), "n_removed": out[0], "kept": out[1], "spans": out[2]}

    kind = next(f.dataType for f in found.schema if f.name == "doc_id").simpleString()
    return map_arrow(found, run, f"doc_id {kind}, t bigint, n_removed bigint, kept string, spans array<struct<first:int,after:int>>")


def repeated_passages(docs: DataFrame, window: int = WINDOW, shard_words: int = SHARD_WORDS, unit_bytes: int = UNIT_BYTES) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 and spans (removed word ranges) of every row of docs.

    A word goes if a window over it has a word sequence that also starts in a document of smaller doc_id; judged on
    the input. Texts of one word sequence are copies: but for those of the least id they go whole, and only one of
    each is searched. Windows are nominated by the anchors that recur in different texts (winnowing: each window
    holds its anchor) and by two 64-bit hashes of the whole window. Each recurring window belongs to the document of
    least id that has it; runs of them there are the passages, which are compiled into automata by shards. Documents
    are streamed through the automata, and what is removed is found there, by words. Sums before shuffles,
    skewed-join splitting and units of bounded size keep a passage that many documents share out of any single task.

    Texts of under window words, null and empty ones keep all words. Rows of a null doc_id stay as they are and
    precede nothing. Rows of an equal doc_id don't precede each other. No rows give no rows.
    """
    rows = settle(_profile(docs, window), "phrases-profile")
    firsts = rows.where(F.col("doc_id").isNotNull() & (F.col("n_words") >= window)).groupBy("key").agg(F.min("doc_id").alias("first_id"))
    firsts = settle(firsts, "phrases-texts")  # both joins with it then have exchanges of their own, which skew can split
    reps = firsts.join(rows.select("key", "doc_id", "anchors"), "key").where("doc_id = first_id").dropDuplicates(["key"])
    each = settle(reps.select("doc_id", "key", F.explode("anchors").alias("anchor")), "phrases-anchors")
    text = F.xxhash64("key")
    recurring = each.groupBy("anchor").agg(F.min(text).alias("a"), F.max(text).alias("z")).where("a < z").select("anchor")
    recurring = settle(recurring, "phrases-recurring")  # so that a hot anchor's rows can be split in the join
    known = each.join(recurring, "anchor").groupBy("doc_id", "key").agg(F.collect_list("anchor").alias("anchors"))

    texts = docs.where(F.col("text").isNotNull()).select("doc_id", "text")
    candidates = _same_text(texts.join(known.withColumnRenamed("key", "key_"), "doc_id"))
    candidates = settle(candidates.select("doc_id", F.xxhash64("key_").alias("t"), "text", "anchors"), "phrases-candidates")
    windows = settle(_windows(candidates, window), "phrases-windows")
    sources = windows.groupBy("w1", "w2").agg(F.min("doc_id").alias("source"), F.max("doc_id").alias("last")).where("source < last")
    sources = settle(sources.drop("last"), "phrases-firsts")
    at = windows.join(sources, ["w1", "w2"]).where("source = doc_id").groupBy("w1", "w2", "doc_id", "t").agg(F.min("pos").alias("pos"))
    at = at.groupBy("doc_id", "t").agg(F.collect_set("pos").alias("at"))
    passages = settle(_passages(candidates.select("doc_id", "t", "text").join(at, ["doc_id", "t"]), window), "phrases-passages")
    found = settle(_locate(passages, candidates, window, shard_words, unit_bytes), "phrases-found")
    found = found.groupBy("doc_id", "t").agg(F.flatten(F.collect_list("spans")).alias("spans"))
    located = _cut(candidates.select("doc_id", "t", "text").join(found, ["doc_id", "t"])).dropDuplicates(["doc_id", "t"])

    out = rows.drop("anchors").join(firsts, "key", "left")
    copies = F.col("first_id").isNotNull() & (F.col("doc_id") > F.col("first_id"))
    located = located.withColumnsRenamed({"doc_id": "id_", "t": "t_"})
    out = out.withColumn("t", F.xxhash64("key")).join(located, (F.col("doc_id") == F.col("id_")) & (F.col("t") == F.col("t_")), "left")
    whole = F.array(F.struct(F.lit(0).alias("first"), F.col("n_words").cast("int").alias("after")))
    return out.select(
        "doc_id",
        "n_words",
        F.when(copies, F.col("n_words")).otherwise(F.coalesce("n_removed", F.lit(0))).cast("long").alias("n_removed"),
        F.when(copies, F.sha2(F.lit(b""), 256)).otherwise(F.coalesce("kept", "sha")).alias("kept_sha256"),
        F.when(copies, whole).otherwise(F.coalesce("spans", F.array().cast("array<struct<first:int,after:int>>"))).alias("spans"),
    )


def _same_text(candidates: DataFrame) -> DataFrame:
    """Rows whose text has the key they were joined for: several texts may stand under one id."""

    def run(batches):
        for batch in batches:
            keys = batch.column("key_").to_pylist()
            yield batch.filter(pa.array([text_key(words_of(t)) == k for t, k in zip(texts_of(batch), keys, strict=True)]))

    return candidates.mapInArrow(run, candidates.schema)


#: The same in DuckDB, over the view documents.
PASSAGES_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT doc_id, k, sha256(array_to_string(w[k : k + 49], ' ')) AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS k FROM d WHERE len(w) >= 50)),
s AS (SELECT g, min(doc_id) AS source FROM g GROUP BY g),
r AS (SELECT DISTINCT doc_id, unnest(range(k, k + 50)) AS p FROM g JOIN s USING (g) WHERE source < doc_id),
x AS (SELECT doc_id, w, unnest(w) AS word, unnest(range(1, len(w) + 1)) AS p FROM d),
k AS (SELECT x.doc_id, string_agg(word, ' ' ORDER BY x.p) AS kept, count(*) AS n_kept FROM x LEFT JOIN r ON r.doc_id = x.doc_id AND r.p = x.p WHERE r.p IS NULL GROUP BY x.doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n_kept, 0))::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256 FROM d LEFT JOIN k USING (doc_id)
"""
