"""Benchmark decontamination: an FM-index of each shard of training text, searched backwards for all test windows."""

from __future__ import annotations

import contextlib
import hashlib
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, texts_of

#: Words of a window; UTF-8 bytes of test items in one broadcast block; words of a shard; distance of sampled positions.
WINDOW = 10
BLOCK_BYTES = 4 << 20
SHARD_WORDS = 1 << 20
SAMPLE = 8
# A-Z become a-z; every ASCII character but letters and digits becomes a space; bytes of other characters stay.
_FOLD = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")


def folded_words(text: str) -> list[bytes]:
    """Runs of characters other than ASCII punctuation, spaces and controls, with A-Z lower-cased, as UTF-8."""
    return text.encode("utf-8", "surrogatepass").translate(_FOLD).split()


def suffix_array(s: np.ndarray) -> np.ndarray:
    """Order of the suffixes of s by prefix doubling; no two symbols 0 count as equal, so comparisons end there."""
    n = len(s)
    if n == 0:
        return np.empty(0, np.int64)
    gaps = s == 0
    rank = np.where(gaps, np.cumsum(gaps) - 1, s.astype(np.int64) + int(gaps.sum()))
    step = 1
    while True:
        after = np.zeros(n, np.int64)
        after[:-step or None] = rank[step:] + 1 if step < n else 0
        key = rank * (int(rank.max()) + 2) + after
        order = np.argsort(key, kind="stable")
        fresh = np.empty(n, np.int64)
        fresh[order] = np.cumsum(np.concatenate([[0], key[order][1:] != key[order][:-1]]))
        rank, step = fresh, step * 2
        if int(rank.max()) == n - 1 or step >= n:
            return order


class WaveletRanks:
    """Wavelet matrix of a symbol sequence: rank of any symbol before any position, for whole arrays at once."""

    def __init__(self, symbols: np.ndarray, top: int):
        self.levels, self.n = max(1, int(top).bit_length()), len(symbols)
        self.zeros, self.before = [], []  # per level: number of zero bits, and zero bits before each position
        for level in reversed(range(self.levels)):
            bits = (symbols >> level) & 1
            self.before.append(np.concatenate([[0], np.cumsum(bits == 0)]).astype(np.int32))
            self.zeros.append(int(self.before[-1][-1]))
            symbols = np.concatenate([symbols[bits == 0], symbols[bits == 1]])

    def rank(self, symbol: np.ndarray, *at: np.ndarray) -> list[np.ndarray]:
        """For each array of positions, how often the symbols occur before them."""
        low, at = np.zeros(len(symbol), np.int64), list(at)
        for k, level in enumerate(reversed(range(self.levels))):
            one, before, zeros = ((symbol >> level) & 1).astype(bool), self.before[k], self.zeros[k]
            low, *at = (np.where(one, zeros + p - before[p], before[p]) for p in (low, *at))
        return [p - low for p in at]


class FMIndex:
    """Backward search and location in a sequence of symbols; 0 parts runs and is in no pattern."""

    def __init__(self, s: np.ndarray, top: int, sample: int = SAMPLE):
        order = suffix_array(s)
        self.bwt = s[order - 1] if len(s) else s
        self.first = np.concatenate([[0], np.cumsum(np.bincount(s, minlength=top + 1))])
        self.ranks = WaveletRanks(self.bwt, top)
        # Starts of runs are sampled besides every sample-th position: a walk never has to cross a 0.
        kept = (order % sample == 0) | (self.bwt == 0)
        self.sampled, self.nth, self.places = kept, np.cumsum(kept) - 1, order[kept]

    def search(self, patterns: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Numbers of the rows of patterns that occur, with their first suffix and that after the last."""
        who = np.arange(len(patterns))
        lo, hi = np.zeros(len(who), np.int64), np.full(len(who), len(self.bwt), np.int64)
        for k in reversed(range(patterns.shape[1])):
            c = patterns[who, k]
            below, upto = self.ranks.rank(c, lo, hi)
            lo, hi = self.first[c] + below, self.first[c] + upto
            live = lo < hi
            who, lo, hi = who[live], lo[live], hi[live]
            if not len(who):
                break
        return who, lo, hi

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Positions of suffixes, walking back from each to the next sampled one."""
        at, out, steps, open_ = rows.copy(), np.empty(len(rows), np.int64), 0, np.arange(len(rows))
        while len(open_):
            known = self.sampled[at]
            out[open_[known]] = self.places[self.nth[at[known]]] + steps
            open_, at = open_[~known], at[~known]
            c = self.bwt[at]
            at, steps = self.first[c] + self.ranks.rank(c, at)[0], steps + 1
        return out


class Windows:
    """Distinct windows of some test items, by their length, as arrays of word numbers over a vocabulary of their words.

    names(n, row) are the items that hold a window: two arrays for each length, offsets and item numbers.
    """

    def __init__(self, items: list[tuple[str, str]], window: int = WINDOW):
        self.vocabulary: dict[bytes, int] = {}
        vocabulary = self.vocabulary
        self.items = [name for name, _ in items]
        rows: dict[int, list] = {}
        for number, (_, text) in enumerate(items):
            ids = np.array([vocabulary.setdefault(w, len(vocabulary) + 1) for w in folded_words(text)], np.int32)
            if size := min(window, len(ids)):
                rows.setdefault(size, []).append((number, np.lib.stride_tricks.sliding_window_view(ids, size)))
        self.by_length, self._owners = {}, {}
        for n in sorted(rows):
            every = np.concatenate([w for _, w in rows[n]])
            owner = np.repeat(np.array([k for k, _ in rows[n]], np.int32), [len(w) for _, w in rows[n]])
            order = np.lexsort((owner, *every.T[::-1]))
            every, owner = every[order], owner[order]
            fresh = np.concatenate([[True], (every[1:] != every[:-1]).any(1)])
            self.by_length[n] = every[fresh]
            self._owners[n] = np.append(np.flatnonzero(fresh), len(owner)).astype(np.int32), owner

    def names(self, n: int, row: int) -> set[str]:
        offsets, owner = self._owners[n]
        return {self.items[k] for k in owner[offsets[row] : offsets[row + 1]]}

    @property
    def shortest(self) -> int:
        return min(self.by_length, default=0)


@contextlib.contextmanager
def held(block, alone: bool):
    """The windows of a broadcast block; unless it is the only one, a worker lets them go afterwards and reads them again for the next shard."""
    yield block.value
    if not alone and getattr(block, "_path", None):
        block.__dict__.pop("_value", None)


def pattern_blocks(items: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> list:
    """Broadcast Windows of at most block_bytes of item text each (or one longer item); driver and tasks hold one block at a time.

    A word of an item takes about 50 bytes, so a block about a tenth of a GB at most.
    """
    blocks, items_held, size = [], [], 0
    sc = items.sparkSession.sparkContext
    for r in items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("")).alias("name"), "text").where("text is not null").toLocalIterator():
        more = len(r["text"].encode("utf-8", "surrogatepass"))
        if items_held and size + more > block_bytes:
            blocks.append(sc.broadcast(Windows(items_held, window)))
            items_held, size = [], 0
        items_held.append((r["name"], r["text"]))
        size += more
    return [*blocks, sc.broadcast(Windows(items_held, window))]


def shard_hits(docs: list[list[bytes]], windows: Windows) -> tuple[list[np.ndarray], list[set]]:
    """Of every document (its words) the sorted hit word numbers and the names of items with occurring windows.

    The index holds the runs of words of the windows' vocabulary that are at least as long as the shortest window:
    no other place can hold an occurrence.
    """
    sizes = np.array([len(d) for d in docs])
    none = [np.empty(0, np.int64) for _ in docs], [set() for _ in docs]
    if not windows.by_length or not sizes.sum():
        return none
    get = windows.vocabulary.get
    ids = np.concatenate([np.array([0, *(get(w, 0) for w in d)], np.int64) for d in docs])
    start = np.concatenate([[0], np.cumsum(sizes + 1)])
    known = np.concatenate([[0], (ids > 0).astype(np.int8), [0]])
    turns = np.flatnonzero(np.diff(known))
    lo, hi = turns[::2], turns[1::2]
    long = hi - lo >= windows.shortest
    lo, hi = lo[long], hi[long]
    if not len(lo):
        return none
    # Each kept run follows one 0; place maps symbols of the index back to the shard.
    size = hi - lo + 1
    place = np.repeat(lo - 1 - np.concatenate([[0], np.cumsum(size)[:-1]]), size) + np.arange(size.sum())
    s = ids[place]
    s[np.concatenate([[0], np.cumsum(size)[:-1]])] = 0
    index = FMIndex(s, len(windows.vocabulary))
    cover, found = np.zeros(len(ids) + 1, np.int64), none[1]
    for n, patterns in windows.by_length.items():
        who, a, z = index.search(patterns)
        if not len(who):
            continue
        count = z - a
        rows = np.repeat(a - np.concatenate([[0], np.cumsum(count)[:-1]]), count) + np.arange(count.sum())
        at = place[index.locate(rows)]
        np.add.at(cover, at, 1)
        np.add.at(cover, at + n, -1)
        doc = np.searchsorted(start, at, side="right") - 1
        for d, w in np.unique(np.stack([doc, np.repeat(who, count)]), axis=1).T:
            found[d].update(windows.names(n, w))
    hit = np.flatnonzero(np.cumsum(cover[:-1]) > 0)
    doc = np.searchsorted(start, hit, side="right") - 1
    cuts = np.searchsorted(doc, np.arange(len(docs) + 1))
    return [hit[a:z] - start[d] - 1 for d, (a, z) in enumerate(zip(cuts, cuts[1:], strict=False))], found


def _shards(texts: list[str], shard_words: int = SHARD_WORDS):
    held, size, lo = [], 0, 0
    for k, t in enumerate(texts):
        held.append(folded_words(t))
        size += len(held[-1])
        if size >= shard_words:
            yield lo, held
            held, size, lo = [], 0, k + 1
    if held:
        yield lo, held


def _hits(texts: list[str], blocks: list, shard_words: int = SHARD_WORDS):
    """Words, hit word numbers and item names of every text, in order."""
    for _, docs in _shards(texts, shard_words):
        hits, names = None, None
        for block in blocks:
            with held(block, len(blocks) == 1) as windows:
                h, n = shard_hits(docs, windows)
            hits = h if hits is None else [np.union1d(a, b) for a, b in zip(hits, h, strict=True)]
            names = n if names is None else [a | b for a, b in zip(names, n, strict=True)]
        yield from zip(docs, hits, names, strict=True)


def removal_spans(hit: np.ndarray) -> list[tuple[int, int]]:
    """Merged (first, after last) word numbers of sorted hit words."""
    if not len(hit):
        return []
    cut = np.flatnonzero(np.diff(hit) > 1) + 1
    return [(int(p[0]), int(p[-1]) + 1) for p in np.split(hit, cut)]


def contamination(docs: DataFrame, items: DataFrame, window: int = WINDOW, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated and spans (merged word ranges) of every row of docs.

    Nothing is shuffled: each task indexes its own whole texts in shards of about SHARD_WORDS words. Null and empty
    texts have no words; items with null text none either; an item without id goes by the empty name; items or rows
    that repeat count as they stand; with no items nothing is hit.
    """
    blocks = pattern_blocks(items, window, block_bytes)
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def run(batch):
        rows = [(len(w), len(h), len(n), hashlib.sha256(",".join(sorted(n)).encode()).hexdigest(), len(h) > 0, [{"first": a, "after": z} for a, z in removal_spans(h)]) for w, h, n in _hits(texts_of(batch), blocks)]
        n_words, n_hit, n_items, sha, bad, spans = zip(*rows, strict=True)
        return {"doc_id": batch.column("doc_id"), "n_words": n_words, "n_hit": n_hit, "n_items": n_items, "items_sha256": sha, "contaminated": bad, "spans": spans}

    return map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, n_words bigint, n_hit bigint, n_items bigint, items_sha256 string, contaminated boolean, spans array<struct<first:int,after:int>>")


def cut_words(text: str, spans: list[tuple[int, int]]) -> str:
    """The text without the words of the spans and what stands between them."""
    at = [m.span() for m in _WORD.finditer(text)]
    out, last = [], 0
    for a, z in spans:
        out.append(text[last : at[a][0]])
        last = at[z - 1][1]
    return "".join([*out, text[last:]])


def decontaminated(docs: DataFrame, items: DataFrame, window: int = WINDOW) -> DataFrame:
    """docs with the merged spans cut out of their texts and n_chars (where there) to match; rows with no word left go.

    Texts without a hit stay as they are, null ones too, whatever the other columns are called.
    """
    blocks = pattern_blocks(items, window)
    schema = docs.schema

    def run(batches):
        for batch in batches:
            texts = texts_of(batch)
            new, keep, changed = batch.column("text").to_pylist(), np.ones(len(texts), bool), {}
            for k, (words, hit, _) in enumerate(_hits(texts, blocks)):
                if len(hit):
                    new[k] = changed[k] = cut_words(texts[k], removal_spans(hit))
                    keep[k] = len(hit) < len(words)
            if changed:
                batch = batch.set_column(batch.schema.get_field_index("text"), "text", pa.array(new, batch.schema.field("text").type))
                if "n_chars" in batch.schema.names and pa.types.is_integer(batch.schema.field("n_chars").type):
                    n = [len(changed[k]) if k in changed else v for k, v in enumerate(batch.column("n_chars").to_pylist())]
                    batch = batch.set_column(batch.schema.get_field_index("n_chars"), "n_chars", pa.array(n, batch.schema.field("n_chars").type))
            yield batch.filter(pa.array(keep))

    return docs.mapInArrow(run, schema)


#: The same in DuckDB, over the views documents and benchmark.
CONTAMINATION_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (SELECT item_id::VARCHAR AS item, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
bw AS (SELECT DISTINCT item, least(10, len(w)) AS n, array_to_string(w[k : k + least(10, len(w)) - 1], ' ') AS g
       FROM (SELECT item, w, unnest(range(1, len(w) - least(10, len(w)) + 2)) AS k FROM b WHERE len(w) > 0)),
dw AS (SELECT doc_id, n, k, array_to_string(w[k : k + n - 1], ' ') AS g
       FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS k FROM d, (SELECT DISTINCT n FROM bw) WHERE len(w) >= n)),
h AS (SELECT DISTINCT dw.doc_id, dw.k, dw.n, bw.item FROM dw JOIN bw ON dw.n = bw.n AND dw.g = bw.g),
c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM h) GROUP BY doc_id),
i AS (SELECT doc_id, count(DISTINCT item) AS n_items, sha256(string_agg(DISTINCT item, ',' ORDER BY item)) AS sha FROM h GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       coalesce(sha, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN c USING (doc_id) LEFT JOIN i USING (doc_id)
"""
