"""FM-index, wavelet ranks and decontamination against brute force."""

import hashlib
import random
import re

import numpy as np
import pytest
from mjoin.llm import decontaminate as D

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def plain_words(text):
    return WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))


def brute(docs, items, window=10):
    for _, text in docs:
        words, hit, names = plain_words(text), set(), set()
        for name, t in items:
            w = plain_words(t)
            n = min(window, len(w))
            wanted = {tuple(w[k : k + n]) for k in range(len(w) - n + 1)} if w else set()
            for k in range(len(words) - n + 1):
                if tuple(words[k : k + n]) in wanted:
                    hit.update(range(k, k + n))
                    names.add("" if name is None else str(name))
        yield len(words), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)


@pytest.mark.parametrize("seed", range(6))
def test_index_counts_and_locates(seed):
    rng = np.random.default_rng(seed)
    s = rng.integers(0, 4, 300)
    s[0] = 0
    order = D.suffix_array(s)
    # every 0 is a symbol of its own, in the order of positions
    distinct = [(int(v), k if v == 0 else -1) for k, v in enumerate(s)]
    assert order.tolist() == sorted(range(len(s)), key=lambda k: distinct[k:])
    ranks = D.WaveletRanks(s, 3)
    at, symbol = rng.integers(0, 301, 50), rng.integers(0, 4, 50)
    assert ranks.rank(symbol, at)[0].tolist() == [int((s[:a] == c).sum()) for a, c in zip(at, symbol, strict=True)]
    index = D.FMIndex(s, 3, sample=5)
    patterns = rng.integers(1, 4, (40, 3))
    who, lo, hi = index.search(patterns)
    found = {w: sorted(index.locate(np.arange(a, z)).tolist()) for w, a, z in zip(who, lo, hi, strict=True)}
    for k, p in enumerate(patterns):
        assert found.get(k, []) == [i for i in range(298) if (s[i : i + 3] == p).all()]


@pytest.mark.parametrize("block_bytes", [1 << 20, 60])
def test_contamination_brute_force(spark, block_bytes):
    rng = random.Random(4)
    some = lambda n: " ".join(rng.choice(["Ab", "b-c", "d", "É", "e9", "ab"]) for _ in range(n))
    items = [(k, some(n)) for k, n in enumerate([12, 11, 10, 3, 1, 25])] + [(7, None), (8, "..."), (None, some(13)), (2, some(11))]
    docs = [(k, f"{some(rng.randint(0, 30))} {rng.choice(items)[1] or ''} {some(rng.randint(0, 9))}") for k in range(60)]
    docs += [(60, None), (61, ""), (61, ""), (62, some(3000)), (None, items[0][1].upper())]
    got = D.contamination(spark.createDataFrame(docs, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string"), block_bytes=block_bytes).collect()
    key = lambda r: (str(r[0]), *r[1:])
    want = [(d[0], *b) for d, b in zip(docs, brute(docs, items), strict=True)]
    assert sorted(map(key, want)) == sorted(key(tuple(r)[:6]) for r in got)
    for r in got:
        assert sum(s["after"] - s["first"] for s in r["spans"]) == r["n_hit"]


def test_cut_texts(spark, odd, none):
    item = "one two three four five six seven eight nine ten"
    items = spark.createDataFrame([(1, item)], "item_id bigint, text string")
    text = f"Before, it. {item.upper()}! After it, (one two) {item}"
    docs = spark.createDataFrame([(1, text, len(text)), (2, item, 48), (3, "clean  text", 11), (4, None, None)], "doc_id bigint, text string, n_chars bigint")
    rows = {r["doc_id"]: r for r in D.decontaminated(docs, items).collect()}
    assert rows[1]["text"] == "Before, it. ! After it, (one two) " and rows[1]["n_chars"] == len(rows[1]["text"])
    assert 2 not in rows and rows[3]["text"] == "clean  text" and rows[4]["text"] is None
    assert D.decontaminated(odd, items).columns == odd.columns and D.decontaminated(odd, items).count() == odd.count()
    assert D.contamination(none, items).count() == 0
    assert not any(r["contaminated"] for r in D.contamination(odd, items.limit(0)).collect())
