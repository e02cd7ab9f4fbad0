"""The n-gram join against all pairs."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest
from mjoin.llm import common
from mjoin.llm import ngram_join as J
from mjoin.llm.common import WordHashes, load, words_of
from pyspark.sql import functions as F


def brute(docs, threshold=0.8, size=5):
    def cut(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        return frozenset(tuple(w[k : k + size]) for k in range(max(1, len(w) - size + 1))) if w else frozenset()

    sets = [cut(t) if i is not None else frozenset() for i, t in docs]
    n, parent = len(docs), list(range(len(docs)))

    def root(k):
        while parent[k] != k:
            k = parent[k]
        return k

    links, texts = [0] * n, [set() for _ in range(n)]
    for a in range(n):
        for b in range(a + 1, n):
            if sets[a] and sets[b] and len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b]):
                links[a] += 1
                links[b] += 1
                if sets[a] != sets[b]:
                    texts[a].add(sets[b])
                    texts[b].add(sets[a])
                parent[root(a)] = root(b)
    least = {}
    for k, (i, _) in enumerate(docs):
        if i is not None:
            least[root(k)] = min(i, least.get(root(k), i))
    rep = {}
    for (i, _), s in zip(docs, sets, strict=True):
        if s:
            rep[s] = min(i, rep.get(s, i))
    return sorted((str(i), str(least.get(root(k))) if i is not None else "None", str(rep.get(sets[k], i)), len(texts[k]), links[k]) for k, (i, _) in enumerate(docs))


def rows_of(frame):
    return sorted((str(r["doc_id"]), str(r["class_id"]), str(r["rep_id"]), r["n_text_links"], r["n_links"]) for r in frame.collect())


def edited(rng, words, share):
    return [rng.choice("uvwxyz") + str(rng.random()) if rng.random() < share else w for w in words]


@pytest.mark.parametrize(("seed", "block"), [(0, 512), (1, 7)])
def test_links_and_classes_of_all_pairs(spark, seed, block):
    rng = random.Random(seed)
    docs, k = [], 0
    for _ in range(12):
        base = [rng.choice("abcdefghijk") + str(rng.randint(0, 50)) for _ in range(rng.randint(3, 250))]
        for _ in range(rng.choice([1, 2, 5, 40])):
            docs.append((k := k + rng.randint(1, 3), " ".join(edited(rng, base, rng.choice([0, 0.005, 0.01, 0.02, 0.04])))))
    rng.shuffle(docs)
    docs += [docs[0], (docs[1][0], docs[2][1]), (900, None), (901, ""), (901, " "), (None, docs[0][1]), (902, "one two"), (903, "one\ttwo"), (904, "two one")]
    got = J.near_duplicates(spark.createDataFrame(docs, "doc_id bigint, text string"), block=block)
    assert rows_of(got) == brute(docs)


def test_whole_small_corpus(spark, sf):
    docs = load(spark, sf, "documents")
    assert rows_of(J.near_duplicates(docs)) == brute([(r["doc_id"], r["text"]) for r in docs.collect()])


def test_prefixes_shrink_by_what_is_found(spark, monkeypatch):
    depth = J.prefix_length(0.8, 24, 0.9999)
    assert J.meeting_chance(0.8, depth) >= 0.9999 > J.meeting_chance(0.8, depth + 1)
    # many links at the threshold let expect losses, the same number of closer ones doesn't
    close, far = np.zeros(J.GRADES), np.zeros(J.GRADES)
    far[0], close[-1] = 20_000, 20_000
    assert J.expected_lost(far, depth) > J.LOST * 20_000 > J.expected_lost(far, depth - 2) and J.expected_lost(close, depth) < 1e-6
    rng = random.Random(2)
    base = [str(rng.random()) for _ in range(400)]
    paths = np.stack([J.signature(J.shingles(words_of(" ".join(edited(rng, base, 0.012))), WordHashes()), depth) for _ in range(400)]).astype(np.uint64)
    keys = J.prefix_keys(paths, depth)
    assert (keys[::2] == keys[1::2]).any(1).sum() >= 198
    # few tries of long prefixes miss links; shrinking finds them again
    docs = spark.createDataFrame([(k, " ".join(edited(rng, base[:60], 0.02))) for k in range(80)], "doc_id bigint, text string")
    want = brute([(r["doc_id"], r["text"]) for r in docs.collect()])
    levels = []
    crowds = J._crowds
    monkeypatch.setattr(J, "_crowds", lambda forest, level, block: levels.append(level) or crowds(forest, level, block))
    assert rows_of(J.near_duplicates(docs, trees=6, recall=0.3, lost=10.0)) != want
    assert len(levels) == 1
    assert rows_of(J.near_duplicates(docs, trees=6, recall=0.3, lost=1e-6)) == want
    assert levels[1:] == list(range(levels[0], levels[-1] - 1, -1)) and len(levels) > 2


def test_the_forest_is_sorted_by_trie_and_path(spark):
    docs = spark.createDataFrame([(k, f"a{k % 7} b c d e f{k}") for k in range(40)], "doc_id bigint, text string")
    rows = J._profile(docs, 3, 4, 5).withColumn("rep", F.col("doc_id")).withColumn("copies", F.lit(1))
    forest = J.plant_forest(rows, 3, 4).collect()
    assert len(forest) == 160 and {len(r["path"]) for r in forest} == {12}
    own = {r["set_key"]: np.frombuffer(r["paths"], ">u4").reshape(4, 3) for r in rows.collect()}
    assert all(bytes(r["path"]) == own[r["set_key"]][r["tree"]].tobytes() for r in forest)


def test_components_of_a_long_chain(spark):
    n = 60
    rng = random.Random(0)
    names = rng.sample(range(10_000), n)
    edges = [(names[k], names[k + 1]) for k in range(n - 1)] + [(20_000, 20_001), (7_777_777, 7_777_777)]
    got = {r["id"]: r["root"] for r in J.components(spark.createDataFrame(edges, "id bigint, other bigint")).collect()}
    assert got == {x: min(names) for x in names} | {20_000: 20_000, 20_001: 20_000}


def test_intersections():
    rng = np.random.default_rng(1)
    a, b = ([np.unique(rng.integers(0, 60, rng.integers(0, 30)).astype(np.uint64)) for _ in range(17)] for _ in range(2))
    got = {(i, j): n for x in J._common(a, b) for i, j, n in zip(*x, strict=True)}
    assert got == {(i, j): n for i, x in enumerate(a) for j, y in enumerate(b) if (n := len(np.intersect1d(x, y)))}


def test_one_of_each(spark, sf, odd, none):
    docs = load(spark, sf, "documents")
    want = {r[1] for r in brute([(r["doc_id"], r["text"]) for r in docs.collect()])}
    kept = J.one_of_each(docs)
    assert kept.columns == docs.columns
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == sorted(want)
    assert sorted(str(r["doc_id"]) for r in J.one_of_each(odd).collect()) == ["1", "2", "3", "4", "5", "6", "None"]
    assert J.one_of_each(odd).columns == odd.columns
    text = "one two three four five six seven"
    rows = [(5, text), (3, text), (5, "quite another text with words of its own"), (7, "short"), (7, "long"), (7, "long"), (8, None), (8, " ")]
    kept = J.one_of_each(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert sorted(map(str, map(tuple, kept))) == sorted(map(str, [rows[1], rows[2], *rows[3:5], *rows[6:]]))
    assert J.near_duplicates(none).count() == J.one_of_each(none).count() == 0


def test_nodes_of_one_set_end_where_the_forest_is_read(spark):
    rng = random.Random(5)
    base = " ".join(str(rng.random()) for _ in range(30))
    docs = [(k, base + f" {k}") for k in range(6)] + [(k, " ".join(str(rng.random()) for _ in range(30))) for k in range(6, 400)]
    keyed = J._profile(spark.createDataFrame(docs, "doc_id bigint, text string"), 3, 4, 5).withColumn("set_id", F.col("doc_id"))
    forest = J.plant_forest(keyed, 3, 4, "set_id")
    nodes = {}
    for r in forest.collect():
        nodes.setdefault((r["tree"], bytes(r["path"])[:8]), set()).add(r["set_id"])
    crowded = {k: v for k, v in nodes.items() if len(v) > 1}
    member, _ = J._crowds(forest, 2, 512)
    kept = {}
    for r in member.collect():
        kept.setdefault((r["tree"], bytes(r["prefix"])), set()).add(r["set_id"])
    assert crowded and crowded.items() <= kept.items() and sum(map(len, kept.values())) < 300 < forest.count()


@pytest.mark.parametrize("size", [1, 2, 3, 50])
def test_neighbours_are_met_across_batches_and_gaps(size):
    rows = [(0, b"aaaa", 1, 0), (0, b"aaab", 2, 1), (0, b"abcc", 3, 2), (0, b"bbbb", 4, 3), (1, b"bbcc", 5, 4), (1, b"bbcd", 6, 5), (1, b"cccc", 7, 6), (1, b"cccd", 8, 9), (1, b"dddd", 9, 10)]
    table = pa.table(dict(zip(("tree", "path", "set_id", "at"), map(list, zip(*rows)), strict=True)), schema=pa.schema([("tree", pa.int32()), ("path", pa.binary()), ("set_id", pa.int64()), ("at", pa.int64())]))
    beside = lambda width: [x for b in J._beside(table.to_batches(max_chunksize=size), width) for x in b.column("set_id").to_pylist()]
    # 1 and 2 share three bytes, 5 and 6 too; 7 and 8 stand at a gap, 1 and 9 at the ends
    assert beside(4) == [1, 7, 8, 9]
    assert beside(3) == [1, 2, 5, 6, 7, 8, 9]


def test_one_of_each_leaves_only_what_its_rows_are_read_from(spark):
    docs = spark.createDataFrame([(k, f"a{k % 3} b c d e f") for k in range(9)], "doc_id bigint, text string")
    before = len(common._SCRATCH)
    kept = J.one_of_each(docs)
    left = common._SCRATCH[before:]
    assert [x.rsplit("mjoin-", 1)[1].rsplit("-", 1)[0] for x in left] == ["ngram-labelled", "ngram-stays"]
    assert sorted(r["doc_id"] for r in kept.collect()) == [0, 1, 2]
