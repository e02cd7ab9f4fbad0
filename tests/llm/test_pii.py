"""Patterns against plain regular expressions, the random field against enumeration, and held-out rows."""

import hashlib
import itertools
import random
import re
import time

import numpy as np
import pytest
from mjoin.llm import pii

PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def plain_spans(text):
    out = []
    for kind, pattern in PLAIN.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m.group())
            good = {
                "email": True,
                "ip": all(int(p) <= 255 for p in m.group().split(".")) if kind == "ip" else 0,
                "card": 14 <= len(digits) <= 19 and pii.luhn(digits),
                "phone": 10 <= len(digits) <= 15,
            }[kind]
            if good:
                out.append((*m.span(), kind))
    return sorted(out, key=lambda s: (s[0], pii.BASE_KINDS.index(s[2])))


@pytest.mark.parametrize("alphabet", ["a@.-b1 ", "12.5 ", "0123456789- ", "+1().- 2345678", "a@b.c+1 0-(x)é"])
def test_patterns_equal_plain_regular_expressions(alphabet):
    rng = random.Random(alphabet)
    for _ in range(3000):
        text = "".join(rng.choice(alphabet) for _ in range(rng.randint(0, 40)))
        assert pii.base_spans(text) == plain_spans(text), text
    assert pii.luhn("4111111111111111") and not pii.luhn("4111111111111112")
    text = "4111 1111-1111 1111, a.b@c.de and 1.2.3.4.5.6.7.8 +1 (555) 010-1234"
    assert pii.base_spans(text) == plain_spans(text) and len(pii.base_spans(text)) == 5


def test_hostile_texts_stay_linear(field):
    began = time.time()
    spans = pii.field_spans(["token = a" + "1." * 100_000 + "b", "token = " + "a1" * 100_000, "the garden, call me at 555-123-4567. " * 20_000, "." * 200_000, "x (at) " * 30_000], field)
    assert len(spans[2]) == 20_000 and time.time() - began < 30
    for text in ("a" * 200_000, "1" * 200_000, "1." * 100_000, "a@" * 100_000, "+1" * 100_000, "é" * 200_000, "1 " * 100_000, "0" * 6000 + ".1.1.1"):
        assert len(pii.base_spans(text)) < 30_000
        pii.field_spans([text], field)
    assert time.time() - began < 60


@pytest.fixture(scope="module")
def field():
    return pii.ChainField.train(pii.example_rows())


def test_viterbi_and_posteriors_by_enumeration():
    rng = np.random.default_rng(0)
    n, most = 3, 4
    emit, step = rng.normal(size=(2, most, n)), rng.normal(size=(n + 1, n))
    real = np.array([[1, 1, 1, 1], [1, 1, 0, 0]], bool)
    post, steps = pii._posteriors(emit, step, real)
    total_steps = np.zeros_like(step)
    for r in range(2):
        size = int(real[r].sum())
        score = lambda p: step[-1][p[0]] + sum(emit[r, t, y] for t, y in enumerate(p)) + sum(step[a, b] for a, b in itertools.pairwise(p))  # noqa: B023, E731
        paths = list(itertools.product(range(n), repeat=size))
        w = np.exp([score(p) for p in paths])
        w /= w.sum()
        for t in range(size):
            assert np.allclose(post[r, t], [sum(x for x, p in zip(w, paths, strict=True) if p[t] == y) for y in range(n)])
        for x, p in zip(w, paths, strict=True):
            total_steps[-1, p[0]] += x
            for a, b in itertools.pairwise(p):
                total_steps[a, b] += x
    assert np.allclose(steps, total_steps)


def test_decoding_by_enumeration(field):
    words = "call 555-123-4567 or mail".split()
    free = np.array([True, True, True, False])
    parts = [field.parts(w) for w in words]
    emit = np.zeros((4, len(pii.LABELS)))
    for k in range(4):
        for j, o in enumerate((-2, -1, 0, 1, 2)):
            if 0 <= k + o < 4:
                emit[k] += parts[k + o][j]
    emit[:, 1:] -= np.where(free, 0, 1e4)[:, None]
    paths = itertools.product(range(len(pii.LABELS)), repeat=4)
    best = max(paths, key=lambda p: field.step[-1][p[0]] + sum(emit[t, y] for t, y in enumerate(p)) + sum(field.step[a, b] for a, b in itertools.pairwise(p)))
    assert field.decode([(words, free), (words[:2], free[:2])])[0].tolist() == list(best)


def test_stretches_lose_nothing(field):
    """The best path over whole texts, by plain Viterbi over every word, equals that of the stretches."""
    rows = pii.example_rows(200, seed=5)
    rng = random.Random(3)
    texts = [[w for _ in range(rng.randint(1, 6)) for w in rng.choice(rows)[0]] + ["green"] * rng.choice([0, 0, 40]) for _ in range(120)]
    for scale in (1.0, 0.2):  # weaker weights let spans reach further
        weak = pii.ChainField(field.names, field.weight * scale, field.step)
        for words, got in zip(texts, weak.decode([(w, np.ones(len(w), bool)) for w in texts]), strict=True):
            parts = [weak.parts(w) for w in words]
            emit = np.array([sum(parts[k + o][j] for j, o in enumerate((-2, -1, 0, 1, 2)) if 0 <= k + o < len(words)) for k in range(len(words))])
            best, back = emit[0] + weak.step[-1], []
            for e in emit[1:]:
                ways = best[:, None] + weak.step[:-1]
                back.append(ways.argmax(0))
                best = ways.max(0) + e
            path = [int(best.argmax())]
            for b in reversed(back):
                path.append(int(b[path[-1]]))
            assert got.tolist() == path[::-1]


def test_held_out_examples(field):
    test = pii.example_rows(300, seed=99)
    right = [[pii.LABELS[y] for y in field.decode([(w, np.ones(len(w), bool))])[0]] == labels for w, labels in test]
    plain = [r for r, (_, labels) in zip(right, test, strict=True) if set(labels) == {"O"}]
    assert np.mean(right) > 0.88 and np.mean(plain) > 0.98


def test_added_spans_and_redaction(spark, odd, none, field):
    text = 'Mail a.b@c.de or call me at 555-123-4567. token = "0123456789abcdef0123456789abcdef" at 10.0.0.1'
    docs = spark.createDataFrame([(1, text), (2, None)], "doc_id bigint, text string")
    rows = {r["doc_id"]: r for r in pii.find_personal_data(docs, field).collect()}
    assert rows[1]["n_spans"] == 4 and rows[2]["n_spans"] == 0
    assert rows[1]["spans"] == "email:5:13,phone:28:40,secret:51:83,ip:88:96"
    base = ",".join(f"{k}:{a}:{z}" for a, z, k in plain_spans(text))
    assert rows[1]["base_sha256"] == hashlib.sha256(base.encode()).hexdigest() and rows[1]["n_phone"] == 0
    assert rows[2]["spans"] == "" and rows[2]["n_email"] == 0
    assert pii.redact(docs, field).collect()[0]["text"] == 'Mail <email> or call me at <phone>. token = "<secret>" at <ip>'
    assert pii.find_personal_data(odd, field).count() == odd.count() and pii.redact(odd, field).columns == odd.columns
    assert pii.redact(odd, field).count() == odd.count() and pii.find_personal_data(none, field).count() == 0


def test_words_without_digits_are_decoded(field):
    """Nothing but the field decides which words are looked at."""
    key = "kJhGfDsAqWeRtYuIoPzXcVbNmLkJhGfDsAqWeRtY"
    texts = ["please write to jane (at) example (dot) com today", "contact bob [at] corner [dot] org", f"token = {key}", "the garden was green and calm"]
    found = [[(t[a:z], k) for a, z, k in s] for t, s in zip(texts, pii.field_spans(texts, field), strict=True)]
    assert found == [[("jane (at) example (dot) com", "email")], [("bob [at] corner [dot] org", "email")], [(key, "secret")], []]
    assert "n:10" in pii.word_features("-" * 250 + "a" * 300) and pii.word_features("1" * 300)[1] == "d:13"
    assert pii.core_span("-" * 250 + "ab)!", 5) == (255, 258)
