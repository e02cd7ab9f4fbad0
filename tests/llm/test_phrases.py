"""Repeated passages against brute force."""

import hashlib
import random
import re

import numpy as np
import pytest
from mjoin.llm import phrases as P
from mjoin.llm.common import window_hashes, words_of


def brute(docs, window):
    split = [re.findall(r"[^\x20\x09-\x0D]+", t or "") for _, t in docs]
    first = {}
    for (i, _), w in zip(docs, split, strict=True):
        for k in range(len(w) - window + 1):
            if i is not None:
                g = tuple(w[k : k + window])
                first[g] = min(i, first.get(g, i))
    for (i, _), w in zip(docs, split, strict=True):
        gone = set()
        for k in range(len(w) - window + 1):
            if i is not None and first[tuple(w[k : k + window])] < i:
                gone.update(range(k, k + window))
        kept = " ".join(x for k, x in enumerate(w) if k not in gone)
        yield str(i), len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()


@pytest.mark.parametrize(("seed", "window"), [(0, 6), (1, 7), (2, 50)])
def test_repeated_passages_brute_force(spark, seed, window):
    rng = random.Random(seed)
    base = [" ".join(rng.choice("ab c d é f".split()) for _ in range(rng.randint(1, 3 * window))) for _ in range(8)]
    docs = []
    for k in rng.sample(range(1000), 70):
        docs.append((k, rng.choice(["\n", " ", "\t "]).join(rng.choice(base) for _ in range(rng.randint(0, 4)))))
    docs += [(2000, docs[0][1]), (2000, docs[0][1]), (2000, docs[1][1] + " x"), (5, None), (6, ""), (None, docs[2][1]), (3, "z " * 5000), (4, "z " * 300)]
    got = P.repeated_passages(spark.createDataFrame(docs, "doc_id bigint, text string"), window).collect()
    assert sorted((str(r[0]), *tuple(r)[1:4]) for r in got) == sorted(brute(docs, window))
    for r in got:
        assert sum(s["after"] - s["first"] for s in r["spans"]) == r["n_removed"]


def test_equal_windows_share_their_anchor():
    rng = np.random.default_rng(0)
    h = rng.integers(0, 1 << 62, 400).astype(np.uint64)
    for window in (2, 3, 10, 50, 51):
        g, least = P.window_anchors(h, window)
        width = P.shingle_width(window)
        assert len(least) == len(h) - window + 1
        assert all(least[k] == g[k : k + window - width + 1].min() for k in range(len(least)))
        assert window_hashes(h[7:], window)[0] == window_hashes(h, window)[7]


@pytest.mark.parametrize("points", [1 << 16, 7])
def test_shards_find_every_window_of_a_passage(points):
    rng = random.Random(5)
    for _ in range(60):
        passages = [(k, [rng.choice([b"a", b"b", b"c"]) for _ in range(rng.randint(9, 40))]) for k in range(3)]
        shard = P.PassageShard(passages, 9, points)
        doc = sum([rng.choice([p[rng.randint(0, 5) :] for _, p in passages] + [[b"q"], [b"a", b"b"]]) for _ in range(4)], [])
        known = {tuple(p[k : k + 9]): None for s, p in passages if s < 2 for k in range(len(p) - 8)}
        want = {i for k in range(len(doc) - 8) if tuple(doc[k : k + 9]) in known for i in range(k, k + 9)}
        assert {i for a, z in shard.cover(doc, 2) for i in range(a, z)} == want


def test_words_decide_in_shards(spark):
    text = " ".join(f"w{k}" for k in range(80))
    docs = spark.createDataFrame([("b", f"x {text} y"), ("a", text), ("c", f"{text[:200]} z")], "doc_id string, text string")
    removed = lambda: {r["doc_id"]: r["n_removed"] for r in P.repeated_passages(docs).collect()}
    assert removed() == {"a": 0, "b": 80, "c": len(text[:200].split()) - 1}
    other = " ".join(f"v{k}" for k in range(80))
    docs = spark.createDataFrame([(1, text), (2, other), (3, f"{other} {text}")], "doc_id bigint, text string")
    assert [r["n_removed"] for r in P.repeated_passages(docs, shard_words=60, unit_bytes=100).orderBy("doc_id").collect()] == [0, 0, 160]
    shard = P.PassageShard([(1, words_of(text))], 50)
    assert shard.cover(words_of(text.replace("w40 ", "V ")), 2) == [] and shard.cover(words_of(text), 1) == []


def test_odd_tables(spark, odd, none):
    assert P.repeated_passages(none).count() == 0
    rows = P.repeated_passages(odd).collect()
    assert len(rows) == odd.count()
    assert {r["doc_id"]: r["n_removed"] for r in rows}[5] == 0


def test_a_very_common_line_is_no_seed_of_passages_with_own_words():
    """Each window of a passage ends in a line that all passages repeat: its seed stands over the own words before it."""
    line = [b"line%d" % k for k in range(7)]
    passages = [(d, [b"a%d_%d" % (d, k) for k in range(5)] + line * 7) for d in range(40)]
    shard = P.PassageShard(passages, 50)
    assert max(len(places) for machine, _ in shard.machines for places in machine.values()) <= 2
    for d, words in passages:
        assert shard.cover([b"x", *words, b"y"], 100) == [(1, 1 + len(words))]
        assert shard.cover(words, d) == []
