"""Token ids as ORC: run-length coded ids in doc_id order, with row indexes, Bloom filters and a manifest of offsets."""

from __future__ import annotations

import os
import re
import zlib
from array import array

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import release_memory, scratch_path

END_ID = 0
#: White space that is neither the space nor the newline, as Unicode or Python have it.
_ODD_SPACE = re.compile("[\t\r\x0b\x0c\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
#: A word of Latin letters before an ASCII sign, digit or newline (RE2): the splitter always parts there.
_WORD_AND_REST = "(?s)^(?P<word>\n?[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]+)(?P<rest>[\n!-@\\[-`{-~].*)$"
_PARTS_LIMIT = 200_000
#: Bytes of texts that are cut up at once.
_CHUNK_BYTES = 3 << 20


class CachedEncoder:
    """Token ids by the tokenizers library, with one call for each distinct part of a text.

    The byte-level splitter never joins across a single space or newline between two other characters, nor a word of
    letters with what follows it, so the parts are encoded alone and remembered; a text in which white space meets white
    space, or that holds the string of an added token (which the library takes for that token), goes to the library whole.
    Arrow cuts a chunk of texts up, numbers its parts and puts their ids together; Python looks up each distinct part once.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks share the cores already
        self.tokenizer = Tokenizer.from_file(path)
        # strings of added tokens are cut out before the splitter: texts that hold one go to the library whole
        added = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.strings, self.added = added, re.compile("|".join(map(re.escape, added))) if added else None
        self.spaced = any(" " in a or "\n" in a for a in added)  # joined words could hold one
        self.known: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        # Ġ is the space in the vocabulary's byte alphabet
        names = {i: t for t, i in self.tokenizer.get_vocab().items()}
        self.leads = np.array([names.get(i, "").startswith("\u0120") for i in range(max(names) + 1)])
        line = self.tokenizer.encode("\n").ids
        self.line = line[0] if len(line) == 1 else None

    def __call__(self, text: str) -> np.ndarray:
        return self.batch([text])[0]

    def batch(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of each text."""
        return [own for _, flat, sizes in self.chunks(pa.array(texts, pa.large_string())) for own in np.split(flat, np.cumsum(sizes)[:-1])]

    def chunks(self, texts: pa.Array):
        """Yields, for runs of texts of a few MB, the first one's place, their ids one after the other, and how many each has; null is the empty text."""
        texts = texts.cast(pa.large_string()).fill_null("")
        chunk = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False)) // _CHUNK_BYTES
        edges = [0, *(np.flatnonzero(np.diff(chunk)) + 1).tolist(), len(texts)]
        for lo, hi in zip(edges, edges[1:], strict=False):
            if hi > lo:
                yield lo, *self._chunk(texts.slice(lo, hi - lo))

    def _chunk(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if len(self.known) > _PARTS_LIMIT:
            self.known, self.older = {}, self.known
        whole = self.uneven(texts)
        cut_up = pc.if_else(pa.array(whole), "", texts)
        # a newline goes with the piece behind it, but in texts with empty lines
        single = pc.if_else(pc.match_substring(cut_up, "\n\n"), False, self.line is not None)
        cut = pc.split_pattern(pc.if_else(single, pc.replace_substring(cut_up, "\n", " \n"), cut_up), " ")
        ends = cut.offsets.to_numpy()
        ends = ends - ends[0]
        begin = ends[:-1]  # pieces without a space before them
        pieces = cut.flatten().dictionary_encode()
        code, pieces = pieces.indices.to_numpy(), pieces.dictionary
        inner = np.ones(len(code), bool)
        inner[begin] = False
        heads = pieces.take(pa.array(code[begin])).to_pylist()
        both = pc.extract_regex(pieces, _WORD_AND_REST)
        word = pc.if_else(both.is_valid(), both.field("word"), pieces)
        rest = pc.if_else(both.is_valid(), both.field("rest"), "")
        sides = []
        for column, before in ((word, ""), (rest, " ")):
            column = column.dictionary_encode()
            at, keys = column.indices.to_numpy(), _strings(column.dictionary, before)
            sides.append((at, keys, list(map(self.known.get, keys))))

        def lacking() -> list[list[int]]:
            used = np.bincount(code[inner], minlength=len(pieces)) > 0
            return [[i for i in np.flatnonzero(np.bincount(at[used], minlength=len(keys))).tolist() if found[i] is None] for at, keys, found in sides]

        lacks = lacking()
        # known parts have been looked through: only first pieces and parts not known can send a text to the library whole
        seen = [*(h.strip("\n") for h in heads), *(keys[i].strip(" \n") for (_, keys, _), some in zip(sides, lacks, strict=True) for i in some)]
        if self.mixed(" ".join(["", *filter(None, seen), ""])):
            odd = np.zeros(len(pieces), bool)
            for (at, keys, _), some in zip(sides, lacks, strict=True):
                flaw = np.zeros(len(keys), bool)
                flaw[[i for i in some if self.mixed(keys[i])]] = True
                odd |= flaw[at]
            whole |= np.logical_or.reduceat(odd[code] & inner, begin) | np.array([self.mixed(h) for h in heads])
            inner &= ~np.repeat(whole, np.diff(ends))
            lacks = lacking()
        self.learn([keys[i] for (_, keys, _), some in zip(sides, lacks, strict=True) for i in some])
        for (_, keys, found), some in zip(sides, lacks, strict=True):
            for i in some:
                found[i] = self.known[keys[i]]
        alone = [texts[i].as_py() if w else h for i, (w, h) in enumerate(zip(whole.tolist(), heads, strict=True))]
        alone = [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(alone, add_special_tokens=False)]
        # parts that nothing but first pieces and whole texts have are left empty
        made = [pa.array(found, pa.large_binary()).fill_null(b"").take(pa.array(at)) for at, _, found in sides]
        ids = pa.concat_arrays([pc.binary_join_element_wise(*made, pa.scalar(b"", pa.large_binary())), pa.array([*alone, b""], pa.large_binary())])
        code = np.where(inner, code, len(ids) - 1)
        code[begin] = len(pieces) + np.arange(len(texts))
        got = ids.take(pa.array(code))
        at = np.frombuffer(got.buffers()[1], np.int64)[: len(got) + 1]
        return np.frombuffer(got.buffers()[2] or b"", np.uint32)[: at[-1] // 4], np.diff(at[ends]) // 4

    def uneven(self, texts: pa.Array) -> np.ndarray:
        """Which texts hold a space beside white space or at the end, or the string of an added token."""
        found = pc.ends_with(texts, " ")
        for x in ("  ", " \n", "\n "):
            found = pc.or_(found, pc.match_substring(texts, x))
        for x in self.strings:
            found = pc.or_(found, pc.match_substring(texts, x))
        return found.to_numpy(zero_copy_only=False).copy()

    def mixed(self, pieces: str) -> bool:
        """Whether pieces, with a space before, between and behind them, hold white space that meets white space, is odd, or an added token."""
        return "  " in pieces or " \n" in pieces or "\n " in pieces or bool(_ODD_SPACE.search(pieces)) or bool(self.added and self.added.search(pieces))

    def learn(self, parts: list[str]) -> None:
        """Ids of new parts: words after a space, lines with the newline before them, and other rests, which have a space before.

        They come from the older half or from the library. Words and lines are encoded as one text each; a word begins at
        an id whose token begins with the space, which stands nowhere else in them, and a line at the id of the newline.
        """
        words, lines, rests = [], [], []
        for p in parts:
            if (had := self.older.get(p)) is not None:
                self.known[p] = had
            elif p[:1] == " " or p == "\n":
                rests.append(p)
            else:
                (lines if p[0] == "\n" else words).append(p)
        encode = lambda texts: self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)
        alone = [(p, p.removeprefix(" ")) for p in rests]
        if self.spaced:  # strings of added tokens could come about between joined words
            alone += [(w, f" {w}") for w in words] + [(x, x) for x in lines]
            words, lines = [], []
        for new, joined in ((words, " " + " ".join(words)), (lines, "".join(lines))):
            if new:
                ids = np.array(encode([joined])[0].ids, np.uint32)
                at = np.flatnonzero(self.leads[ids] if new is words else ids == self.line).tolist()
                raw = ids.tobytes()
                for p, a, z in zip(new, at, [*at[1:], len(ids)], strict=True):
                    self.known[p] = raw[4 * a : 4 * z]
        for (p, _), e in zip(alone, encode([t for _, t in alone]), strict=True):
            self.known[p] = array("I", e.ids).tobytes()


def _strings(column: pa.Array, before: str) -> list[str]:
    """The strings of a column, none of which holds a space, with a text before those that are not empty."""
    if not len(column):
        return []
    joined = pc.binary_join(pa.ListArray.from_arrays(pa.array([0, len(column)], pa.int32()), column), pa.scalar(" ", pa.large_string()))
    return [before + x for x in joined[0].as_py().split(" ")] if before else joined[0].as_py().split(" ")


_ENCODERS: dict[str, CachedEncoder] = {}


def encoder_for(path: str) -> CachedEncoder:
    """One encoder for each vocabulary and Python worker, so that later tasks find its pieces known."""
    if path not in _ENCODERS:
        release_memory()  # what earlier stages left to this worker
        _ENCODERS[path] = CachedEncoder(path)
    return _ENCODERS[path]


def write_token_files(docs: DataFrame, tokenizer_path: str, path: str, partitions: int | None = None, end_id: int = END_ID, stripe_bytes: int = 16 << 20, row_stride: int = 1000) -> None:
    """Encode every text and write ORC files under path: ids/ (in doc_id order) and offsets/ (ids before each file part).

    Rows are dealt by ranges of (doc_id, hash of the text), so that no id count is needed beforehand and a repeated
    doc_id still spreads; null ids come first, null texts count as empty, repeated rows are all written. Ids are
    signed 32-bit integers, which ORC stores run-length coded. Each file carries row indexes for every row_stride
    rows and Bloom filters on doc_id. A rerun task writes the same rows: order has no open ties but equal rows.
    """
    spark = docs.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    tie = F.xxhash64("text")
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()
    schema = f"part int, doc_id {kind}, local_start bigint, n_tokens int, ids array<int>"
    arrow = pa.schema([("part", pa.int32()), ("doc_id", pa.string() if kind == "string" else pa.int64() if kind == "bigint" else pa.int32()), ("local_start", pa.int64()), ("n_tokens", pa.int32()), ("ids", pa.list_(pa.int32()))])

    def encode(batches):
        from pyspark import TaskContext

        encoder, part, at = encoder_for(tokenizer_path), TaskContext.get().partitionId(), 0
        for batch in batches:
            for lo, flat, sizes in encoder.chunks(batch.column("text")):
                flat, sizes = np.insert(flat, np.cumsum(sizes), end_id), sizes + 1
                ends = np.cumsum(sizes)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], ends]), pa.int32()), pa.array(flat.view(np.int32)))
                ids = batch.column("doc_id").slice(lo, len(sizes)).cast(arrow.field("doc_id").type)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(sizes), part, np.int32)), ids, pa.array(at + ends - sizes), pa.array(sizes, pa.int32()), lists], schema=arrow)
                at += int(ends[-1])

    dealt = docs.select("doc_id", "text").repartitionByRange(n, F.col("doc_id"), tie).sortWithinPartitions(F.col("doc_id"), tie)
    # fixed values: names of ORC writer options
    options = {"orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01", "orc.row.index.stride": str(row_stride), "orc.create.index": "true", "orc.stripe.size": str(stripe_bytes), "orc.compress": "ZSTD"}
    dealt.mapInArrow(encode, schema).write.mode("overwrite").options(**options).orc(f"{path}/ids")

    # One row for each written part: their number is the number of range partitions, not of documents.
    sums = spark.read.orc(f"{path}/ids").groupBy("part").agg(F.sum("n_tokens").cast("long").alias("n")).collect()
    before, rows = 0, []
    for r in sorted(sums, key=lambda r: r["part"]):
        rows.append((r["part"], before))
        before += r["n"]
    spark.createDataFrame(rows, "part int, before bigint").coalesce(1).write.mode("overwrite").orc(f"{path}/offsets")


def read_token_files(spark: SparkSession, path: str, doc_ids: list | None = None) -> DataFrame:
    """doc_id, start, n_tokens and ids of a written set; doc_ids prunes stripes by their statistics and Bloom filters."""
    ids = spark.read.orc(f"{path}/ids")
    if doc_ids is not None:
        ids = ids.where(F.col("doc_id").isin(list(doc_ids)))
    offsets = F.broadcast(spark.read.orc(f"{path}/offsets"))  # a row for each file part
    return ids.join(offsets, "part").select("doc_id", (F.col("before") + F.col("local_start")).alias("start"), "n_tokens", "ids")


def token_digest(tokens: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens and the unsigned crc32 of the ids as little-endian unsigned 32-bit integers."""
    kind = next(f.dataType for f in tokens.schema if f.name == "doc_id").simpleString()

    def digest(batches):
        for b in batches:
            lists = b.column("ids")
            flat, ends = lists.flatten().to_numpy(zero_copy_only=False).astype("<u4", copy=False), np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False))])
            crcs = [zlib.crc32(flat[a:z].tobytes()) for a, z in zip(ends, ends[1:], strict=False)]
            yield pa.RecordBatch.from_pydict({"doc_id": b.column("doc_id"), "start": b.column("start"), "n_tokens": pa.array(np.diff(ends), pa.int64()), "ids_crc32": pa.array(crcs, pa.int64())})

    return tokens.select("doc_id", "start", "ids").mapInArrow(digest, f"doc_id {kind}, start bigint, n_tokens bigint, ids_crc32 bigint")


def token_table(docs: DataFrame, tokenizer_path: str, path: str | None = None) -> DataFrame:
    """Write the token files of docs (to a scratch folder unless path is given), read them back and digest them."""
    path = path or scratch_path(docs.sparkSession, "tokens")
    write_token_files(docs, tokenizer_path, path)
    return token_digest(read_token_files(docs.sparkSession, path))
