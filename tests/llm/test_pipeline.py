"""Every stage of the pipeline against brute force on what its predecessor kept."""

import zlib
from collections import Counter

import corpus_pipeline as C
import numpy as np
from mjoin.llm import mixing, toxicity
from mjoin.llm.common import load, settle
from mjoin.llm.queries import vocabulary
from tokenizers import Tokenizer

from .test_decontaminate import brute as brute_hits
from .test_ngram_join import brute as brute_classes


def test_stages(spark, sf):
    docs = load(spark, sf, "documents")
    columns = docs.columns
    model = toxicity.fit(docs, load(spark, sf, "labels"))
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    out = {}
    for name, stage in C.STAGES:
        out[name] = docs = settle(stage(spark, docs, sf), f"test-{name}")
        assert name == "token_files" or docs.columns == columns
    texts = {k: {r["doc_id"]: r["text"] for r in v.collect()} for k, v in out.items() if k != "token_files"}

    assert texts["toxicity"] == {i: t for i, t in before.items() if model.score(t or "") < 0.5}
    classes = brute_classes(list(texts["toxicity"].items()))
    assert set(map(str, texts["ngram_join"])) == {c[1] for c in classes}
    items = [(r["item_id"], r["text"]) for r in load(spark, sf, "benchmark").collect()]
    kept = list(texts["ngram_join"].items())
    for (i, t), (n, hit, *_) in zip(kept, brute_hits(kept, items), strict=True):
        if not hit:
            assert texts["decontamination"][i] == t
        elif hit < n:
            assert n - hit >= next(brute_hits([(i, texts["decontamination"][i])], items))[0] > 0
        else:
            assert i not in texts["decontamination"]
    want = {r["doc_id"]: r["repeats"] for r in mixing.mix(out["decontamination"]).collect() if r["repeats"]}
    mixed = out["mixing"].collect()
    assert Counter(r["doc_id"] for r in mixed) == want
    assert all(r["n_chars"] == len(r["text"]) for r in mixed)

    encode, start = Tokenizer.from_file(vocabulary()).encode, 0
    for r, d in zip(out["token_files"].orderBy("start").collect(), sorted(mixed, key=lambda r: r["doc_id"]), strict=True):
        ids = [*encode(d["text"], add_special_tokens=False).ids, 0]
        assert tuple(r) == (d["doc_id"], start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert sorted(map(tuple, C.run(spark, sf).collect())) == sorted(map(tuple, out["token_files"].collect()))


def test_odd_rows_pass_every_stage(spark, sf, odd, none):
    for rows in (odd, none):
        docs = rows
        for name, stage in C.STAGES:
            docs = settle(stage(spark, docs, sf), f"test-odd-{name}")
            if name != "token_files":
                assert docs.columns == rows.columns
        assert (docs.count() > 0) == (rows is odd)
