"""Operators 1, 3, 5, 9 and 10 against brute force, round trips and held-out rows."""

import functools
import hashlib
import random
import unicodedata
import zlib
from collections import Counter

import numpy as np
import pytest
from mjoin.llm import langid, mixing, queries, sketch, token_files, toxicity
from mjoin.llm.common import load, mix64
from tokenizers import Tokenizer


def test_mix_reaches_targets_and_reruns_agree(spark, sf):
    rows = queries.op1_mix_sources(spark, sf).toPandas()
    again = queries.op1_mix_sources(spark, sf).toPandas()
    assert rows.sort_values("doc_id").taken.tolist() == again.sort_values("doc_id").taken.tolist()
    assert (rows.taken <= 3 * rows["size"]).all()
    by = rows.groupby("source").agg(size=("size", "sum"), taken=("taken", "sum"), target=("target", "first"), most=("size", "max"))
    assert ((by.taken - by.target).abs() <= by.most / 2 + 1).all()
    assert abs(by.target.sum() - by["size"].sum()) < 1e-6 * by["size"].sum()
    assert (by.target <= 3 * by["size"] + 1e-9).all()


def test_water_filling_by_repeated_clamping(spark):
    rng = random.Random(5)
    sizes = {f"s{i}": rng.choice([0, 1, 5, 40, 300]) for i in range(12)} | {None: 17}
    order = sorted((s for s in sizes if s is not None)) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    total, capped = sum(sizes.values()), {}
    while True:
        rest = total - sum(capped.values())
        live = [s for s in order if s not in capped]
        share = {s: rest * weight[s] / sum(weight[x] for x in live) for s in live}
        over = [s for s in live if share[s] > 3 * sizes[s]]
        if not over:
            break
        capped |= {s: 3 * sizes[s] for s in over}
    want = capped | share
    got = mixing.source_targets(spark.createDataFrame(list(sizes.items()), "source string, size bigint")).collect()
    assert {r["source"]: pytest.approx(r["target"]) for r in got} == want


def test_mixed_documents_follow_the_decisions(spark, sf, odd):
    docs = load(spark, sf, "documents")
    want = {r["doc_id"]: r["repeats"] for r in mixing.mix(docs).collect() if r["repeats"]}
    got = mixing.mixed_documents(docs)
    assert got.columns == docs.columns
    assert {r["doc_id"]: r["count"] for r in got.groupBy("doc_id").count().collect()} == want
    assert mixing.mix(odd).count() == odd.count()
    assert mixing.mixed_documents(odd).columns == odd.columns
    mixing.mixed_documents(odd).collect()


def test_empty_tables(spark, none):
    labels = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    path = queries.vocabulary()
    assert mixing.mix(none).count() == mixing.mixed_documents(none).count() == 0
    assert sketch.fingerprints(none).count() == 0
    assert langid.identify(none, langid.learn_profiles(none)).count() == 0
    assert toxicity.score(none, toxicity.fit(none, labels)).count() == 0
    assert token_files.token_table(none, path).count() == 0


def test_pieces_encode_as_the_library_does():
    encoder = token_files.CachedEncoder(queries.vocabulary())
    rng, plain = random.Random(1), Tokenizer.from_file(queries.vocabulary())
    assert encoder("a <|endoftext|> b").tolist() == [64, 220, 50256, 275]
    parts = ["a", "B", " ", "  ", "\n", "\t", "'s", "don't", "é", "1", "2", "!", "　", "<|endoftext|>", "漢", "\r"]
    for _ in range(4000):
        text = "".join(rng.choice(parts) for _ in range(rng.randint(0, 14)))
        assert encoder(text).tolist() == plain.encode(text, add_special_tokens=False).ids, text


def test_token_files_round_trip(spark, sf, odd, tmp_path):
    docs, path = load(spark, sf, "documents"), f"file://{tmp_path}/set"
    token_files.write_token_files(docs, queries.vocabulary(), path, partitions=4)
    got = token_files.token_digest(token_files.read_token_files(spark, path)).orderBy("doc_id").collect()
    encoder, start = Tokenizer.from_file(queries.vocabulary()), 0
    for r, d in zip(got, docs.orderBy("doc_id").collect(), strict=True):
        ids = [*encoder.encode(d["text"] or "", add_special_tokens=False).ids, 0]
        assert (r["doc_id"], r["start"], r["n_tokens"]) == (d["doc_id"], start, len(ids))
        assert r["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    some = token_files.read_token_files(spark, path, doc_ids=[3, 77])
    assert sorted(r["doc_id"] for r in some.collect()) == [3, 77]
    assert "In(doc_id, [3,77])" in some._jdf.queryExecution().toString()
    rows = token_files.token_table(odd, queries.vocabulary()).orderBy("start").collect()
    assert len(rows) == odd.count() and sum(r["n_tokens"] for r in rows[:-1]) == rows[-1]["start"]
    assert rows[0]["doc_id"] is None


def brute_fingerprints(docs):
    order = sorted(docs, key=lambda d: -d[0])
    for (i, t), (_, u) in zip(order, order[1:] + order[:1], strict=True):
        half = len(t) // 2
        edited = t[: len(t) - half] + u[:half]
        yield i, len(t), hashlib.sha256(edited.encode()).hexdigest(), t, edited, u


@pytest.mark.parametrize("partitions", [1, 3, 16])
def test_fingerprints_brute_force(spark, sf, partitions):
    docs = load(spark, sf, "documents")
    got = {r["doc_id"]: r for r in sketch.fingerprints(docs, partitions).collect()}
    want = list(brute_fingerprints([(r["doc_id"], r["text"] or "") for r in docs.collect()]))
    assert len(got) == len(want)
    for i, n, sha, t, edited, u in want:
        a, e, b = map(sketch.sketch, (t, edited, u))
        r = got[i]
        assert (r["n_chars"], r["edited_sha256"], r["fingerprint"], r["edited_fingerprint"]) == (n, sha, sketch.encode(a), sketch.encode(e))
        assert (r["near_edited"], r["near_next"]) == (sketch.likeness(a, e), sketch.likeness(a, b))
    assert np.mean([r["near_edited"] for r in got.values()]) > 0.4


def test_fingerprints_of_text_ids(spark):
    rng = random.Random(6)
    docs = [(f"{rng.choice('aZé')}{k}", " ".join(rng.choice("abcde") for _ in range(rng.randint(0, 40)))) for k in range(90)]
    frame = spark.createDataFrame(docs, "doc_id string, text string")
    for partitions in (1, 7):
        got = {r["doc_id"]: r["edited_sha256"] for r in sketch.fingerprints(frame, partitions).collect()}
        order = sorted(docs, reverse=True)
        want = {}
        for (i, t), (_, u) in zip(order, order[1:] + order[:1], strict=True):
            want[i] = hashlib.sha256((t[: len(t) - len(t) // 2] + u[: len(t) // 2]).encode()).hexdigest()
        assert got == want


def test_sketches_merge_and_estimate():
    rng = random.Random(3)
    text = "".join(rng.choice("abcdefgh ") for _ in range(40_000))
    a, b = text[:25_000], text[10_000:]
    grams = lambda t: {t[i : i + 16] for i in range(len(t) - 15)}
    true = len(grams(a) & grams(b)) / min(len(grams(a)), len(grams(b)))
    assert abs(sketch.likeness(sketch.sketch(a), sketch.sketch(b)) - true) < 0.1
    whole = sketch.merge(sketch.sketch(a), sketch.sketch(b))
    assert whole.tolist() == sketch.sketch(text).tolist()
    assert sketch.decode(sketch.encode(whole)).tolist() == whole.tolist()
    assert sketch.likeness(sketch.sketch(""), sketch.sketch("")) == 1 and sketch.likeness(sketch.sketch(""), whole) == 0


def test_odd_rows(spark, odd, sf):
    assert sketch.fingerprints(odd).count() == odd.count()
    rows = {r["doc_id"]: r for r in langid.identify(odd, langid.learn_profiles(load(spark, sf, "documents"))).collect()}
    assert rows[2]["lang_pred"] == rows[3]["lang_pred"] == rows[4]["lang_pred"] == "und" and rows[3]["score"] == 0
    labels = spark.createDataFrame([(1, 1), (1, 0), (2, None), (7, 0), (None, 1)], "doc_id bigint, toxic int")
    scores = toxicity.score(odd, toxicity.fit(odd, labels)).collect()
    assert len(scores) == odd.count() and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in scores)


def test_held_out_languages(spark, sf):
    sf = sf.replace("0.001", "0.01")
    docs = {r["doc_id"]: r for r in load(spark, sf, "documents").collect()}
    rows = queries.op10_language_id(spark, sf).collect()
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in rows)
    held = [r for r in rows if r["held_out"] and docs[r["doc_id"]]["lang"]]
    assert np.mean([r["lang_pred"] == docs[r["doc_id"]]["lang"] for r in held]) > 0.95


def test_languages_brute_force(spark):
    """Counts, ranks and distances with plain strings and dictionaries."""
    rng = random.Random(8)
    words = {"xx": ["aba", "cab", "bca'd", "ñu"], "yy": ["dod", "\u0915\u093f\u0924", "odo", "ÀB"]}
    rows = [(k, " ".join(rng.choice(words[lang]) for _ in range(rng.randint(1, 9))) + rng.choice(["", "! 12 ½", " ②"]), lang) for k, lang in enumerate(["xx", "yy"] * 15)]
    rows += [(100, "½ ② Ⅷ 12", "xx"), (101, None, "yy"), (102, "cab dod", None), (None, "odo", "yy")]

    def counts(text):
        out = Counter()
        inside = "".join(c if unicodedata.category(c)[0] in "LM" else " " for c in (text or "").lower())
        for w in inside.split():
            out.update(w)
            out.update(f" {w} "[k : k + n] for n in (2, 3) for k in range(len(w) + 3 - n))
        return out

    def ranks(c):
        code = lambda g: functools.reduce(lambda s, x: s << 21 | (ord(x) if x != " " else 1), g, 0)
        return {g: k for k, g in enumerate(sorted(c, key=lambda g: (-c[g], code(g)))[:400])}

    profiles = {}
    for lang in ("xx", "yy"):
        total = Counter()
        for i, t, own in rows:
            if own == lang and zlib.crc32(b"" if i is None else str(i).encode()) % 5:
                total.update(counts(t))
        profiles[lang] = ranks(total)
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    got = {r["doc_id"]: r for r in langid.identify(docs, langid.learn_profiles(docs)).collect()}
    assert got[100]["lang_pred"] == got[101]["lang_pred"] == "und"
    for i, t, _ in rows:
        if own := ranks(counts(t)):
            d = {lang: sum(abs(p[g] - k) if g in p else 400 for g, k in own.items()) / 400 / len(own) for lang, p in profiles.items()}
            best = min(d, key=lambda lang: (d[lang], lang))
            assert got[i]["lang_pred"] == best and abs(got[i]["score"] - (1 - d[best])) < 1e-12
            assert got[i]["held_out"] == (zlib.crc32(b"" if i is None else str(i).encode()) % 5 == 0)


def test_toxicity_brute_force(spark):
    """Features, ratios and the gradient of the fitted weights, recomputed with plain loops; repeated ids count once."""
    rng = random.Random(4)
    rows = [(k, " ".join(rng.choice(["good", "calm", "green", "vile" if k % 3 == 0 else "kind"]) for _ in range(6)), int(k % 3 == 0)) for k in range(60)]
    docs = spark.createDataFrame([(k, t) for k, t, _ in rows] + [(3, rows[3][1])] * 50, "doc_id bigint, text string")
    labels = spark.createDataFrame([(k, y) for k, _, y in rows], "doc_id bigint, toxic int")
    sample = toxicity.labelled_sample(docs, labels, 20).collect()
    learned = sorted((k for k, _, _ in rows if zlib.crc32(str(k).encode()) % 5), key=str)
    assert len(sample) == 20 and {r["text"] for r in sample} <= {t for k, t, _ in rows if k in set(learned)}
    model = toxicity.fit(docs, labels)

    def slots(text):
        points = [ord(c) + 7 for c in f" {text.lower()} "]
        mixed = [int(x) for x in mix64(np.array(points, np.uint64))]
        out = set()
        for n in toxicity.LENGTHS:
            for k in range(len(mixed) - n + 1):
                h = functools.reduce(lambda s, x: (s * 0x9E3779B97F4A7C15 + x) % 2**64, mixed[k : k + n], 0)
                out.add(int(mix64(np.array([h], np.uint64))[0]) >> (64 - toxicity.BITS))
        return out

    own = [(slots(t), y) for k, t, y in rows if k in set(learned)]
    n = [sum(y == c for _, y in own) for c in (0, 1)]
    counts, got_n = toxicity.presence(toxicity.labelled_sample(docs, labels))
    ratio = toxicity.log_count_ratios(counts, got_n)
    assert got_n.tolist() == n
    for s in set().union(*(f for f, _ in own)):
        seen = [sum(s in f for f, y in own if y == c) for c in (0, 1)]
        assert counts[:, s].tolist() == seen
        assert abs(ratio[s] - np.log((seen[1] + 1) / (n[1] + 2) / ((seen[0] + 1) / (n[0] + 2)))) < 1e-12
    for k, t, y in rows:
        margin = sum(float(model.value[s]) for s in slots(t)) + model.bias
        assert abs(model.score(t) - 1 / (1 + np.exp(-margin))) < 1e-6 and (model.score(t) >= 0.5) == ("vile" in t)


def test_out_of_place_distance_by_hand():
    profiles = {"x": np.array([1, 2, 3]), "y": np.array([3, 9])}
    r = langid.Ranker(profiles, most=3)
    assert r.ranks[np.searchsorted(r.codes, [1, 2, 3, 9])].tolist() == [[0, 3], [1, 3], [2, 0], [3, 1]]


def test_held_out_toxicity(spark, sf):
    sf = sf.replace("0.001", "0.1")
    labels = {r["doc_id"]: r["toxic"] for r in load(spark, sf, "labels").collect()}
    rows = [r for r in queries.op5_toxicity(spark, sf).collect() if r["held_out"] and r["doc_id"] in labels]
    toxic, clean = ([r["predicted"] for r in rows if labels[r["doc_id"]] == y] for y in (1, 0))
    assert np.mean(toxic) > 0.6 and np.mean(clean) < 0.01


def test_known_pieces_are_not_looked_through_again():
    """Only the first piece and unknown ones are searched for odd white space; ids stay those of the library."""
    import public_tokenizers
    from mjoin.llm.token_files import CachedEncoder
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    encoder, plain, seen = CachedEncoder(path), Tokenizer.from_file(path), []
    look = encoder.mixed
    encoder.mixed = lambda pieces: seen.append(pieces) or look(pieces)
    texts = ["one two three", "zero two three two", "zero\ttwo three", "one two\n three", " two three", "two ", "a  b", "two <|endoftext|> three", "", "\ntwo three", "two three\n", "one two three　"]
    for _ in range(2):
        assert [x.tolist() for t in texts for x in encoder.batch([t])] == [plain.encode(t, add_special_tokens=False).ids for t in texts]
    assert seen[1] == " zero "


def test_parts_of_many_texts_encode_as_the_library_does(monkeypatch):
    """Lines and words are encoded apart from what follows them and put together in chunks of texts, whole texts among them."""
    monkeypatch.setattr(token_files, "_CHUNK_BYTES", 200)
    monkeypatch.setattr(token_files, "_PARTS_LIMIT", 40)
    encoder, plain, rng = token_files.CachedEncoder(queries.vocabulary()), Tokenizer.from_file(queries.vocabulary()), random.Random(3)
    even = ["a", "word", " ", " ", "\n", "'s", "don't", "é", "Über", "1", "!", "漢", ". ", ",\n", "²", "́", "ªb", "_", "%%%"]
    odd = [*even, "  ", "\n\n", "\t", "　", "<|endoftext|>", "\r", "\0", "\x1f"]
    for k in range(300):
        texts = ["".join(rng.choice(odd if k % 2 else even) for _ in range(rng.randint(0, 14))) for _ in range(30)]
        assert [x.tolist() for x in encoder.batch(texts)] == [plain.encode(t, add_special_tokens=False).ids for t in texts]
    assert encoder.batch([]) == []
    # a word learned with one sign behind it is known with any other, and behind a newline as a line
    encoder.batch(["b words, lines\nlines"])
    known = set(encoder.known)
    encoder.batch(["b words. words! words lines,\nlines."])
    assert set(encoder.known) - known == {" .", " !", " ,"} - known
