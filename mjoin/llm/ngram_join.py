"""N-gram Jaccard join: a MinHash LSH forest nominates pairs, exact shingle sets decide; links and classes, not pairs, leave a task."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import WordHashes, map_arrow, mix64, settle, settle_alone, texts_of, window_hashes, words_of

#: Words of a shingle, least similarity, tries of the forest, longest prefix, the recall that each pair is sure of, and the
#: share of all links that may be lost (as expected from those found) when prefixes stop shrinking.
SHINGLE = 5
THRESHOLD = 0.8
TREES = 24
LONGEST_PREFIX = 12
RECALL = 0.9999
LOST = 1e-6
#: Classes of similarity between the threshold and 1 in which found links are counted.
GRADES = 40
#: Members of one block of a crowded node; increments of one counting step.
BLOCK = 512
_STEP = 1 << 22


def shingles(words: list[bytes], hashes: WordHashes, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the runs of size words; fewer words are one shingle, none give none."""
    h = hashes(words)
    return np.unique(window_hashes(h, min(size, len(h)))) if len(h) else np.empty(0, np.uint64)


def meeting_chance(similarity, depth: int, trees: int = TREES):
    """Probability that two sets share a prefix of depth values in one of the tries."""
    return 1 - (1 - similarity**depth) ** trees


def prefix_length(threshold: float = THRESHOLD, trees: int = TREES, recall: float = RECALL, longest: int = LONGEST_PREFIX) -> int:
    """Values of a signature in each trie: the longest prefix at which pairs of the least similarity still meet with the recall."""
    return next((d for d in range(longest, 1, -1) if meeting_chance(threshold, d, trees) >= recall), 1)


def expected_lost(grades: np.ndarray, depth: int, threshold: float = THRESHOLD, trees: int = TREES) -> float:
    """Links that never met, as expected from the links found by grade of similarity: each found one stands for 1 / its chance."""
    least = threshold + (1 - threshold) * np.arange(len(grades)) / len(grades)
    return float((grades * (1 / meeting_chance(least, depth, trees) - 1)).sum())


def _factors(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20240)
    return rng.integers(1, 1 << 32, count, dtype=np.uint32) | np.uint32(1), rng.integers(0, 1 << 32, count, dtype=np.uint32)


def signature(s: np.ndarray, depth: int, trees: int = TREES) -> np.ndarray:
    """MinHash values of a set, (trees, depth): the path of the set in each trie."""
    a, b = _factors(depth * trees)
    x, low = (s >> np.uint64(32)).astype(np.uint32), np.full(depth * trees, 0xFFFFFFFF, np.uint32)
    for lo in range(0, len(x), 256):  # blocks that stay in the cache
        np.minimum(low, (x[lo : lo + 256, None] * a + b).min(0), out=low)
    return low.reshape(trees, depth)


def prefix_keys(paths: np.ndarray, depth: int) -> np.ndarray:
    """(sets, trees): one 64-bit key of the first depth values of each path in paths (sets, trees, values)."""
    key = np.broadcast_to(np.arange(1, paths.shape[1] + 1, dtype=np.uint64), paths.shape[:2])
    for level in range(depth):
        key = mix64(key * np.uint64(0x9E3779B97F4A7C15) + paths[:, :, level])
    return key


def _profile(docs: DataFrame, depth: int, trees: int, size: int) -> DataFrame:
    """doc_id, mark (a hash of the text), set_key, n_shingles and paths (big-endian, trie by trie, so that bytes sort as values do) of every row."""
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def run(batch):
        hashes, key, n, paths = WordHashes(), [], [], []
        for t in texts_of(batch):
            s = shingles(words_of(t), hashes, size)
            n.append(len(s))
            key.append(xxhash.xxh3_128_digest(s.tobytes()))
            paths.append(signature(s, depth, trees).astype(">u4").tobytes() if len(s) else None)
        return {"doc_id": batch.column("doc_id"), "mark": batch.column("mark"), "set_key": key, "n_shingles": n, "paths": paths}

    return map_arrow(docs.select("doc_id", "text", F.xxhash64("text").alias("mark")), run, f"doc_id {kind}, mark bigint, set_key binary, n_shingles int, paths binary")


def _common(a: list[np.ndarray], b: list[np.ndarray]):
    """Yields (rows of a, rows of b, sizes of intersections) for the pairs of sets that share anything, in steps."""
    flat_b = np.concatenate(b)
    own_b = np.repeat(np.arange(len(b)), [len(x) for x in b])
    order = np.argsort(flat_b, kind="stable")
    values, own_b = flat_b[order], own_b[order]
    lo, work = 0, 0
    spans = [(np.searchsorted(values, x, side="left"), np.searchsorted(values, x, side="right")) for x in a]
    for hi in range(len(a)):
        work += int((spans[hi][1] - spans[hi][0]).sum())
        if work < _STEP and (hi - lo + 1) * len(b) < _STEP and hi + 1 < len(a):
            continue
        cell = []
        for r in range(lo, hi + 1):
            first, after = spans[r]
            n = after - first
            at = np.repeat(first - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
            cell.append((r - lo) * len(b) + own_b[at])
        shared = np.bincount(np.concatenate(cell), minlength=(hi - lo + 1) * len(b))
        at = np.flatnonzero(shared)
        yield lo + at // len(b), at % len(b), shared[at]
        lo, work = hi + 1, 0


def verified_links(members: list[dict], others: list[dict] | None, tree: int, depth: int, threshold: float):
    """Rows (of members, of others) and similarity of the pairs that are alike enough and first meet here; each unordered pair once.

    A pair meets first at its longest common prefix, and there in the first of the tries that have it.
    """
    right = members if others is None else others
    paths_a, paths_b = (np.stack([m["paths"] for m in x]) for x in (members, right))
    here_a, here_b = prefix_keys(paths_a, depth)[:, :tree], prefix_keys(paths_b, depth)[:, :tree]
    longer = depth < paths_a.shape[2]
    deep_a, deep_b = (prefix_keys(x, depth + 1) for x in (paths_a, paths_b)) if longer else (None, None)
    size_a, size_b = (np.array([len(m["set"]) for m in x]) for x in (members, right))
    out = []
    for i, j, shared in _common([m["set"] for m in members], [m["set"] for m in right]):
        every = size_a[i] + size_b[j] - shared
        # shared / every >= threshold, without rounding at the bound
        good = shared >= threshold * every - 1e-9
        if others is None:
            good &= i < j
        i, j, alike = i[good], j[good], shared[good] / every[good]
        for lo in range(0, len(i), 1 << 16):
            a, b = i[lo : lo + (1 << 16)], j[lo : lo + (1 << 16)]
            known = (here_a[a] == here_b[b]).any(1)
            if longer:
                known |= (deep_a[a] == deep_b[b]).any(1)
            out.append(np.stack([a, b, alike[lo : lo + (1 << 16)]])[:, ~known])
    i, j, alike = np.concatenate(out, axis=1) if out else np.empty((3, 0))
    return i.astype(np.int64), j.astype(np.int64), alike


def _block_pairs(rows: DataFrame, threshold: float, size: int, depth: int, longest: int) -> DataFrame:
    """Rows (node, part, side, tree, set_id, set_key, copies, paths, text) of one block pair to links by set, a spanning forest, and (without a set) numbers of links by grade.

    A text that has another set than its row names is left out.
    """
    schema = pa.schema([("set_id", pa.int64()), ("other", pa.int64()), ("text_links", pa.int64()), ("links", pa.int64()), ("grades", pa.list_(pa.int64()))])

    def run(table: pa.Table) -> pa.Table:
        hashes, sides = WordHashes(), ([], [])
        for r in table.to_pylist():
            own = shingles(words_of(r["text"]), hashes, size)
            if xxhash.xxh3_128_digest(own.tobytes()) == r["set_key"]:
                paths = np.frombuffer(r["paths"], ">u4").astype(np.uint64).reshape(-1, longest)
                sides[r["side"]].append({"id": r["set_id"], "copies": r["copies"], "paths": paths, "set": own})
        tree = table.column("tree")[0].as_py()
        left, right = (sorted(s, key=lambda m: m["id"]) for s in sides)
        if not left:  # a block whose partner has no members
            return schema.empty_table()
        i, j, alike = verified_links(left, right or None, tree, depth, threshold)
        right = right or left
        n_a, n_b = np.array([m["copies"] for m in left]), np.array([m["copies"] for m in right])
        names = sorted({m["id"] for m in (*left, *right)})
        place = {x: k for k, x in enumerate(names)}
        a, b = np.array([place[m["id"]] for m in left])[i], np.array([place[m["id"]] for m in right])[j]
        ends = np.concatenate([a, b])
        texts = np.bincount(ends, minlength=len(names))
        links = np.bincount(ends, np.concatenate([n_b[j], n_a[i]]), len(names)).astype(np.int64)
        # Spanning forest of the links: every set points at the least set of its part of this block.
        root = np.arange(len(names))
        while True:
            least = root.copy()
            np.minimum.at(least, a, root[b])
            np.minimum.at(least, b, root[a])
            least = least[least]
            if (least == root).all():
                break
            root = least
        some = np.flatnonzero(texts)
        if not len(some):
            return schema.empty_table()
        grade = np.minimum(((alike - threshold) / max(1 - threshold, 1e-9) * GRADES + 1e-6).astype(int), GRADES - 1)
        grades = [None] * len(some) + [np.bincount(np.maximum(grade, 0), minlength=GRADES).tolist()]
        name = lambda ks: pa.array([*(names[k] for k in ks), None], pa.int64())
        return pa.Table.from_arrays([name(some), name(root[some]), pa.array([*texts[some], 0]), pa.array([*links[some], 0]), pa.array(grades, pa.list_(pa.int64()))], schema=schema)

    return rows.groupBy("node", "part").applyInArrow(run, "set_id bigint, other bigint, text_links bigint, links bigint, grades array<bigint>")


def components(edges: DataFrame, label: str = "components") -> DataFrame:
    """(id, root): the least id of the connected component of every id in edges (id, other).

    Alternates hooking to the least neighbour and jumping over pointers until nothing changes; every round is a
    shuffle of the ids and edges, written to the shared folder. Hot ids only meet grouped minima.
    """
    both = settle(edges.where("id <> other").select("id", "other").distinct(), label)
    both = both.unionByName(both.select(F.col("other").alias("id"), F.col("id").alias("other")))
    state = settle(both.groupBy("id").agg(F.least(F.min("other"), F.col("id")).alias("root")), label)
    while True:
        known = state.select(F.col("id").alias("other"), F.col("root").alias("of_other"))
        around = both.join(known, "other").groupBy("id").agg(F.min("of_other").alias("near"))
        hooked = settle(state.join(around, "id").select("id", F.least("root", "near").alias("to"), (F.col("near") < F.col("root")).alias("moved")), label)
        jump = hooked.select(F.col("id").alias("to"), F.col("to").alias("of_to"))
        state = settle(hooked.join(jump, "to").select("id", F.least("to", "of_to").alias("root"), "moved"), label)
        if not state.where("moved").limit(1).count():
            return state.select("id", "root")


def plant_forest(keyed: DataFrame, depth: int, trees: int, name: str = "set_key") -> DataFrame:
    """The tries as one table (tree, path, name, at), sorted by trie and path: sets of one prefix stand side by side, at consecutive numbers at."""
    width = 4 * depth
    path = F.transform(F.sequence(F.lit(0), F.lit(trees - 1)), lambda t: F.substring("paths", t * width + 1, F.lit(width)))
    forest = keyed.select(name, F.posexplode(path).alias("tree", "path")).repartitionByRange("tree", "path").sortWithinPartitions("tree", "path")
    return settle(forest.withColumn("at", F.monotonically_increasing_id()), "ngram-forest")


def _beside(batches, width: int):
    """Rows (tree, path, set_id, at) whose neighbour has the same trie and first width bytes, or isn't in sight (another task may have it)."""
    kept = None

    def flags(batch):
        path = batch.column("path").cast(pa.binary(len(batch.column("path")[0].as_py())))
        size = path.type.byte_width
        bytes_ = np.frombuffer(path.buffers()[1], np.uint8)[path.offset * size : (path.offset + len(path)) * size].reshape(-1, size)[:, :width]
        at, tree = (batch.column(c).to_numpy() for c in ("at", "tree"))
        near = at[1:] == at[:-1] + 1
        return ~near | ((tree[1:] == tree[:-1]) & (bytes_[1:] == bytes_[:-1]).all(1))

    def out(batch, keep):
        prefix = pc.binary_slice(batch.column("path"), 0, width).cast(pa.binary())
        return pa.RecordBatch.from_arrays([batch.column("tree"), prefix, batch.column("set_id")], ["tree", "prefix", "set_id"]).filter(pa.array(keep))

    for batch in batches:
        if not batch.num_rows:
            continue
        if kept is not None:
            batch = pa.concat_batches([kept[0], batch])
        met = flags(batch)
        before = np.concatenate([[True if kept is None else kept[1]], met])
        after = np.concatenate([met, [True]])
        # the last row waits for its neighbour in the next batch
        yield out(batch.slice(0, batch.num_rows - 1), (before | after)[:-1])
        kept = batch.slice(batch.num_rows - 1), bool(before[-1])
    if kept is not None:
        yield out(kept[0], np.array([True]))


def _crowds(forest: DataFrame, depth: int, block: int) -> tuple[DataFrame, DataFrame]:
    """Nodes of a level of the tries with several sets (n and two sums that name their members), and a table with all their members.

    Sorted tries have the sets of a node side by side, so nearly all of the nodes of one set end where they are read.
    """
    member = settle(forest.mapInArrow(lambda batches: _beside(batches, 4 * depth), "tree int, prefix binary, set_id bigint"), "ngram-crowds")
    print_of = F.xxhash64("set_id")
    nodes = member.groupBy("tree", "prefix").agg(F.count("*").alias("n"), F.sum(print_of % 1_000_000_007).alias("p"), F.bit_xor(print_of).alias("q")).where("n > 1")
    # of nodes with equal members only that of the first trie
    return member, settle(nodes.groupBy("n", "p", "q").agg(F.min(F.struct("tree", "prefix")).alias("x")).select("n", "p", "q", "x.tree", "x.prefix"), "ngram-nodes")


def _paired(member: DataFrame, nodes: DataFrame, block: int) -> DataFrame:
    """node, tree, set_id, part and side of the members of nodes; a block meets itself and every other block once."""
    blocks = F.greatest(F.lit(1), F.ceil(F.col("n") / block)).cast("int")
    chosen = member.join(nodes.select("tree", "prefix", blocks.alias("blocks")), ["tree", "prefix"])
    chosen = chosen.withColumn("own", F.pmod(F.xxhash64(F.lit("block"), "set_id"), F.col("blocks")).cast("int"))
    # part = (smaller, larger) block, side 1 is the larger
    part = lambda o: F.struct((F.least(o, F.col("own")) * F.col("blocks") + F.greatest(o, F.col("own"))).alias("part"), (o < F.col("own")).cast("int").alias("side"))
    pairs = F.explode(F.transform(F.sequence(F.lit(0), F.col("blocks") - 1), part))
    return settle(chosen.select(F.xxhash64("tree", "prefix").alias("node"), "tree", "set_id", pairs.alias("x")).select("node", "tree", "set_id", "x.part", "x.side"), "ngram-members")


def _links(docs: DataFrame, keyed: DataFrame, depth: int, trees: int, threshold: float, size: int, block: int, lost: float) -> DataFrame:
    """Links by set, spanning edges and grades, from prefixes that shrink until so small a share of links is expected to be lost."""
    forest, done, found, grades = plant_forest(keyed, depth, trees, "set_id"), None, None, np.zeros(GRADES)
    for level in range(depth, 0, -1):
        member, nodes = _crowds(forest, level, block)
        # what a longer prefix has brought together already is not worked again
        fresh = nodes if done is None else nodes.join(done, ["n", "p", "q"], "left_anti")
        chosen = _paired(member, fresh, block)
        work = _with_texts(docs, chosen.join(keyed, "set_id")).select("node", "part", "side", "tree", "set_id", "set_key", "copies", "paths", "text")
        now = settle(_block_pairs(work, threshold, size, level, depth), "ngram-links")
        for r in now.select(F.posexplode("grades").alias("grade", "n")).groupBy("grade").agg(F.sum("n").alias("n")).collect():  # GRADES rows
            grades[r["grade"]] += r["n"]
        found = now if found is None else found.unionByName(now)
        if expected_lost(grades, level, threshold, trees) <= lost * grades.sum():
            break
        done = nodes.select("n", "p", "q") if done is None else done.unionByName(nodes.select("n", "p", "q"))
    return found.where("set_id is not null").drop("grades")


def _labelled(docs: DataFrame, threshold: float, size: int, trees: int, recall: float, block: int, lost: float) -> DataFrame:
    """What near_duplicates gives, with set_key and the least set of the class, which is null for rows without shingles or id."""
    depth = prefix_length(threshold, trees, recall)
    rows = settle(_profile(docs, depth, trees, size), "ngram-profile")
    has_sets = F.col("doc_id").isNotNull() & (F.col("n_shingles") > 0)
    real = rows.where(has_sets)
    keyed = real.groupBy("set_key").agg(F.min(F.struct("doc_id", "mark")).alias("x"), F.count("*").alias("copies"), F.first("paths").alias("paths"))
    # a set's short id is a number, as written here
    keyed = settle(keyed.select("set_key", F.monotonically_increasing_id().alias("set_id"), F.col("x.doc_id").alias("rep"), "x.mark", "copies", "paths"), "ngram-keys")
    sets = keyed.drop("paths", "mark")
    if real.groupBy("doc_id", "mark").count().where("count > 1").limit(1).count():
        docs = docs.select("doc_id", "text").where("doc_id is not null and text is not null").distinct()
    found = _links(docs, keyed, depth, trees, threshold, size, block, lost)
    links = found.groupBy("set_id").agg(F.sum("text_links").alias("text_links"), F.sum("links").alias("links"))
    roots = components(found.select(F.col("set_id").alias("id"), "other")).withColumnRenamed("id", "set_id")
    roots = roots.join(sets.select("set_id", "rep"), "set_id")
    classes = roots.join(settle(roots.groupBy("root").agg(F.min("rep").alias("class_id")), "ngram-classes"), "root").select("set_id", "class_id", "root")

    by_set = sets.join(links, "set_id", "left").join(classes, "set_id", "left")
    by_set = settle(by_set.select("set_key", F.coalesce("root", "set_id").alias("root"), F.col("rep").alias("rep_id"), F.coalesce("class_id", "rep").alias("class_id"), F.coalesce("text_links", F.lit(0)).alias("n_text_links"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links")), "ngram-by-set")
    names = ["doc_id", "class_id", "rep_id", "n_text_links", "n_links", "set_key", "root"]
    none = F.lit(0).cast("long")
    alone = rows.where(~has_sets).select("doc_id", F.col("doc_id").alias("class_id"), F.col("doc_id").alias("rep_id"), none.alias("n_text_links"), none.alias("n_links"), "set_key", F.lit(None).cast("bigint").alias("root"))
    return real.select("doc_id", "set_key").join(by_set, "set_key").select(*names).unionByName(alone)


def near_duplicates(docs: DataFrame, threshold: float = THRESHOLD, size: int = SHINGLE, trees: int = TREES, recall: float = RECALL, block: int = BLOCK, lost: float = LOST) -> DataFrame:
    """doc_id, class_id, rep_id, n_text_links and n_links of every row of docs.

    class_id is the least id linked by any chain of pairs of similarity threshold or more (Jaccard, on sets of size
    words), rep_id the least id of the rows of an equal shingle set, n_text_links the number of different sets
    linked to the row's own, n_links the number of other rows linked to the row, equal sets included.

    Rows of one shingle set meet in a grouped count, not in pairs; one row stands for them. Each trie of the forest is
    a sorted table of MinHash paths. Sets meet at the longest prefix at which pairs of the threshold meet with the
    recall; prefixes then shrink value by value until the links found, each weighed by its chance to meet, let expect no
    more than the share lost of all links to be missing. Nodes of equal member sets are worked once, a pair where it first meets.
    Nodes beyond block members are cut into blocks, every two of which are a task of bounded size; tasks return counts
    and spanning edges, never pairs. What the tries nominate, whole shingle sets decide. Nothing is capped or sampled.

    Rows whose text is null, empty or white space have no shingles and no links; their class is their own id, even
    where several rows share it. Rows of a null id are their own, with null ids and no links. An empty table
    gives an empty result.
    """
    return _labelled(docs, threshold, size, trees, recall, block, lost).select("doc_id", "class_id", "rep_id", "n_text_links", "n_links")


def _with_texts(docs: DataFrame, chosen: DataFrame) -> DataFrame:
    """Rows of chosen with the text of their id and mark, a hash that tells the texts of one id apart; sets are compared by their digests."""
    texts = docs.where("text is not null").select(F.col("doc_id").alias("rep"), F.xxhash64("text").alias("mark"), "text")
    return texts.join(chosen, ["rep", "mark"])


def one_of_each(docs: DataFrame, threshold: float = THRESHOLD, size: int = SHINGLE, trees: int = TREES, recall: float = RECALL, block: int = BLOCK, lost: float = LOST) -> DataFrame:
    """The rows of docs that stay when one row of each class stays: one of the class's own id, and of equal texts one.

    Rows without shingles or without an id all stay, with all their columns. Rows that share an id but not the text
    are told apart by their shingle sets.
    """
    rows = settle_alone(docs.sparkSession, lambda: _labelled(docs, threshold, size, trees, recall, block, lost), "ngram-labelled")
    own = rows.where("doc_id = class_id and root is not null").groupBy("root").agg(F.min(F.struct("doc_id", "set_key")).alias("x"))
    stays = settle(own.select("x.doc_id", "x.set_key").withColumnsRenamed({"doc_id": "kept_id_", "set_key": "kept_key_"}), "ngram-stays")
    by_id = rows.where("doc_id is not null").groupBy(F.col("doc_id").alias("id_")).agg(F.count("*").alias("n_"), F.max(F.col("root").isNull()).alias("blank_"))
    once = by_id.join(stays.select("kept_id_").distinct(), F.col("id_") == F.col("kept_id_"), "left")
    once = once.where("n_ > 1 or blank_ or kept_id_ is not null").select("id_", "n_")
    near = docs.join(once, docs["doc_id"] == F.col("id_"), "left").where(F.col("n_").isNotNull() | docs["doc_id"].isNull())
    names = [docs[c] for c in docs.columns]
    if not rows.where("doc_id is not null").groupBy("doc_id").count().where("count > 1").limit(1).count():
        return near.select(*names)
    blank = F.col("text").isNull() | ~F.col("text").rlike(r"[^\x20\x09-\x0D]")
    sure = (F.coalesce("n_", F.lit(1)) == 1) | blank
    again = near.where(~sure).select(F.struct(*names).alias("row_"), F.col("doc_id").alias("again_id_"), F.col("text").alias("again_text_"))
    key = F.pandas_udf(lambda texts: _set_keys(texts, size), "binary")
    again = again.withColumn("again_key_", key("again_text_")).join(stays, (F.col("again_id_") == F.col("kept_id_")) & (F.col("again_key_") == F.col("kept_key_")))
    again = again.dropDuplicates(["again_id_", "again_key_"]).select("row_.*")
    return near.where(sure).select(*names).unionByName(again)


def _set_keys(texts, size: int):
    hashes = WordHashes()
    return texts.map(lambda t: xxhash.xxh3_128_digest(shingles(words_of(t), hashes, size).tobytes()))
