"""Personal data: fixed patterns, and a linear-chain conditional random field over word shapes that adds spans."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import map_arrow, texts_of

#: Kinds of the patterns in the order of equal starts; kinds that only the random field finds follow.
BASE_KINDS = ("email", "ip", "card", "phone")
FIELD_KINDS = ("email", "phone", "ssn", "iban", "secret")
KINDS = (*BASE_KINDS, *(k for k in FIELD_KINDS if k not in BASE_KINDS))
LABELS = ("O", *(f"{p}-{k}" for k in FIELD_KINDS for p in "BI"))
#: Characters of text whose words are held at once, words (with padding) that are decoded at once, and words that are remembered.
HELD, CELLS, TABLE = 1 << 20, 1 << 15, 300_000
_OFFSETS = (-2, -1, 0, 1, 2)

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_DOTTED = re.compile(r"[0-9]++(?:\.[0-9]++)*+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        v = int(d) * (1 + k % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns: leftmost, non-overlapping within a kind, failing matches dropped.

    Written so that no text takes quadratic time: an e-mail grows from its @, an ip from a whole dotted run.
    """
    found, last = [], 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            last = m.end()
            found.append((start, last, "email"))
        at = text.find("@", max(at + 1, last))
    if _DIGIT.search(text):
        for run in _DOTTED.finditer(text):
            if run.group().count(".") >= 3:
                parts, pos = run.group().split("."), run.start()
                for k in range(0, len(parts) - 3, 4):
                    four = parts[k : k + 4]
                    end = pos + sum(map(len, four)) + 3
                    if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in four):
                        found.append((pos, end, "ip"))
                    pos = end + 1
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 14:
                digits = re.sub(r"[^0-9]", "", m.group())
                if 14 <= len(digits) <= 19 and luhn(digits):
                    found.append((*m.span(), "card"))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 10 <= len(_DIGIT.findall(m.group())) <= 15:
                    found.append((*m.span(), "phone"))
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


# ---- the random field ---------------------------------------------------------------------------------------------

_CHUNK = re.compile(r"\S+")
_BEFORE = re.compile(r"[^\w@+(]*")
_SHAPE = str.maketrans({**dict.fromkeys("abcdefghijklmnopqrstuvwxyz", "x"), **dict.fromkeys("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "X"), **dict.fromkeys("0123456789", "d")})


_RUNS = re.compile(r"(.)\1+", re.S)
_KEY = re.compile(r"[A-Za-z0-9_-]+")


def word_features(chunk: str) -> tuple[str, ...]:
    """Shape features of a word between white space."""
    a, z = core_span(chunk, 0)
    core = chunk[a:z]
    shape = core.translate(_SHAPE)
    digits = shape.count("d")
    out = [f"s:{_RUNS.sub(r'\1', shape)[:16]}", f"d:{min(digits, 13)}", f"n:{min(len(core), 40) // 4}"]
    if len(shape) <= 14:
        out.append(f"f:{shape}")
    if len(core) >= 24 and digits >= 3 and len(core) - digits >= 3 and _KEY.fullmatch(core):
        out.append("key")
    if not digits:
        out.append(f"w:{core.lower()}")
    return tuple(out)


def core_span(chunk: str, start: int) -> tuple[int, int]:
    a, z = 0 if chunk[:1].isalnum() else _BEFORE.match(chunk).end(), len(chunk)
    while z > a and not (chunk[z - 1].isalnum() or chunk[z - 1] in "_)"):
        z -= 1
    return start + a, start + z


def labelled_examples(spark: SparkSession, rows: int = 600, seed: int = 11) -> DataFrame:
    """The small labelled table: words and their labels, made by rule from invented sentences and values."""
    return spark.createDataFrame(example_rows(rows, seed), "words array<string>, labels array<string>")


def example_rows(rows: int = 600, seed: int = 11) -> list[tuple[list[str], list[str]]]:
    rng = random.Random(seed)
    num = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    key = lambda n, s: "".join(rng.choice(s) for _ in range(n))
    name = lambda: key(rng.randint(3, 8), "abcdefghiklmnoprstuw")
    letters, tops = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", ["com", "org", "net"]
    values = {
        "phone": lambda: rng.choice([f"({num(3)}) {num(3)}-{num(4)}", f"{num(3)}-{num(3)}-{num(4)}", f"{num(3)}.{num(3)}.{num(4)}", f"{num(3)} {num(3)} {num(4)}", f"0{num(3)} {num(7)}", f"0{num(2)} {num(4)} {num(4)}", f"0{num(3)}/{num(6)}"]),
        "ssn": lambda: f"{num(3)}-{num(2)}-{num(4)}",
        "iban": lambda: (lambda b: rng.choice([b, " ".join(b[i : i + 4] for i in range(0, len(b), 4))]))(f"{key(2, 'DEFRGBNLATCH')}{num(20)}"),
        "email": lambda: rng.choice([f"{name()} (at) mail{num(1)} (dot) com", f"{name()}{num(2)} [at] {name()} [dot] org", f"{name()}{num(1)}@{name()}", f"{name()} (at) {name()} (dot) {rng.choice(tops)}", f"{name()} [at] {name()} [dot] {rng.choice(tops)}"]),
        "secret": lambda: key(rng.choice([32, 40, 64]), rng.choice(["0123456789abcdef", "0123456789abcdef", letters])),
    }
    # fixed values: words that come before personal data
    lead = {
        "phone": ["call me at", "phone:", "tel.", "my number is", "mobile", "fax", "reach us on", "Telefon", "llamar al", "appelez le"],
        "ssn": ["SSN", "ssn:", "social security number", "my social is", "tax id"],
        "iban": ["IBAN", "iban:", "account", "please transfer to", "Konto", "cuenta", "compte"],
        "email": ["mail me:", "write to", "email", "contact", "e-mail:", "reach me under"],
        "secret": ["token =", "api_key =", "password:", "secret =", "key:", "export TOKEN ="],
    }
    plain = [
        lambda: num(4), lambda: num(rng.randint(1, 3)), lambda: f"{num(2)}.{num(2)}.{num(4)}", lambda: f"{num(4)}-{num(2)}-{num(2)}", lambda: f"{num(1)}.{num(1)}.{num(2)}", lambda: f"{num(1)},{num(3)}", lambda: f"${num(3)}.{num(2)}",
        lambda: f"{num(2)}:{num(2)}", lambda: f"{num(3)} of {num(3)}", lambda: f"{num(1)} {num(2)} {num(3)}", lambda: f"{num(rng.randint(5, 16))}", lambda: f"+{num(1)} ({num(3)}) {num(3)}-{num(4)}", lambda: f"{num(3)}.{num(2)}.{num(2)}.{num(3)}", lambda: f"{name()}.{num(2)}@mail{num(1)}.example.com",
        lambda: f"x{num(2)}", lambda: f"{name()}{num(2)}", lambda: f"{num(4)}-{num(4)}-{num(4)}-{num(4)}", lambda: f"v{num(1)}.{num(1)}", lambda: f"ISBN {num(3)}-{num(1)}-{num(3)}-{num(5)}-{num(1)}", lambda: f"page {num(2)}", lambda: f"{num(2)}%",
        lambda: f"{name()} ({name()}) {name()}", lambda: f"[{name()}] {name()}", lambda: "-".join(name() for _ in range(5)), lambda: f"{name()}{name()}{name()}", lambda: f"{name()} at {name()} dot {name()}",
    ]
    wrap = ["{}", "{}.", "{},", '"{}"', "{}###", "{}!!", "{}&&&", "({})"]
    words = lambda n: [(f"{rng.choice([name(), name().title()])}{rng.choice(['', '', '', ',', '.'])}", "O") for _ in range(n)]
    out = []
    for _ in range(rows):
        tokens = words(rng.randint(0, 6))
        if rng.random() < 0.6:
            kind = rng.choice(FIELD_KINDS)
            tokens += [(w, "O") for w in rng.choice(lead[kind]).split()]
            value = values[kind]()
            value = rng.choice(wrap[:5]).format(value) if kind != "email" else value
            tokens += [(w, f"{'I' if k else 'B'}-{kind}") for k, w in enumerate(value.split())]
        else:
            tokens += [(w, "O") for w in rng.choice(wrap).format(rng.choice(plain)()).split()]
        tokens += words(rng.randint(0, 6))
        out.append(([t[0] for t in tokens], [t[1] for t in tokens]))
    return out


class ChainField:
    """Weights of the features at each offset, of label steps, and of first labels; all in numpy."""

    def __init__(self, names: dict[tuple, int], weight: np.ndarray, step: np.ndarray):
        self.names, self.weight, self.step = names, weight, step
        self.offset = np.array([o - _OFFSETS[0] for o, _ in names], np.int64)
        self.words = {f[2:] for _, f in names if f.startswith("w:")}
        self.rows: dict[str, int] = {}
        self.shapes: dict[tuple[str, str], int] = {}
        self.sets: dict[tuple[int, ...], int] = {}
        self.table, self.most = np.zeros((1024, len(_OFFSETS), len(LABELS))), np.zeros((1024, len(_OFFSETS)))

    @staticmethod
    def allowed() -> np.ndarray:
        """0 where label b may follow label a (the last row: at the start), a large negative number elsewhere."""
        out = np.zeros((len(LABELS) + 1, len(LABELS)))
        for b, to in enumerate(LABELS):
            if to[0] == "I":
                for a, before in enumerate((*LABELS, "")):
                    if before[2:] != to[2:] or not before:
                        out[a, b] = -1e4
        return out

    @classmethod
    def train(cls, rows: list[tuple[list[str], list[str]]], epochs: int = 60, rate: float = 0.15, ridge: float = 1e-3) -> ChainField:
        """Maximum likelihood with a ridge by adaptive gradient steps over the whole table, padded into one batch."""
        names: dict[tuple, int] = {}
        seqs = [[[names.setdefault((o, f), len(names)) for o in _OFFSETS if 0 <= k + o < len(words) for f in word_features(words[k + o])] for k in range(len(words))] for words, _ in rows]
        most, n = max(len(s) for s in seqs), len(LABELS)
        flat = np.array([f for s in seqs for fs in s for f in fs])
        cell = np.repeat([r * most + k for r, s in enumerate(seqs) for k in range(len(s))], [len(fs) for s in seqs for fs in s])
        sizes = np.array([len(s) for s in seqs])
        real = np.arange(most) < sizes[:, None]
        gold = np.zeros((len(rows), most), int)
        for r, (_, labels) in enumerate(rows):
            gold[r, : len(labels)] = [LABELS.index(x) for x in labels]
        weight, step = np.zeros((len(names), n)), np.zeros((n + 1, n))
        g_weight, g_step = np.full_like(weight, 1e-6), np.full_like(step, 1e-6)
        seen = np.zeros((len(rows) * most, n))
        seen[np.flatnonzero(real.ravel()), gold.ravel()[real.ravel()]] = 1
        gold_step = np.zeros_like(step)
        np.add.at(gold_step, (np.full(len(rows), n), gold[:, 0]), 1)
        both = real[:, 1:]
        np.add.at(gold_step, (gold[:, :-1][both], gold[:, 1:][both]), 1)
        fixed = cls.allowed()
        for _ in range(epochs):
            emit = np.stack([np.bincount(cell, weight[flat, y], len(rows) * most) for y in range(n)], 1).reshape(len(rows), most, n)
            post, steps = _posteriors(emit, step + fixed, real)
            wrong = (post * real[:, :, None]).reshape(-1, n) - seen
            grad = np.stack([np.bincount(flat, wrong[cell, y], len(names)) for y in range(n)], 1) / len(rows) + ridge * weight / 10
            grad_step = (steps - gold_step) / len(rows) + ridge * step
            g_weight += grad**2
            g_step += grad_step**2
            weight -= rate * grad / np.sqrt(g_weight)
            step -= rate * grad_step / np.sqrt(g_step)
        return cls(names, weight, step + fixed)

    def parts(self, chunk: str) -> np.ndarray:
        """What a word adds to the label scores of the words at each offset from it."""
        return self._sum(self._known(word_features(chunk)))

    def _known(self, features: tuple[str, ...]) -> tuple[int, ...]:
        return tuple(i for f in features for o in _OFFSETS if (i := self.names.get((o, f))) is not None)

    def _sum(self, ids: tuple[int, ...]) -> np.ndarray:
        out = np.zeros((len(_OFFSETS), len(LABELS)))
        np.add.at(out, self.offset[list(ids)], self.weight[list(ids)])
        return out

    def numbers(self, words: list[str]) -> np.ndarray:
        """Rows of the words in the table of parts: a row for each set of features that the field knows, row 0 for no word.

        Rows of words and of shapes are remembered until there are TABLE of them; the table grows with the sets alone.
        """
        rows, shapes = self.rows, self.shapes
        if len(rows) > TABLE:
            rows.clear()
        if len(shapes) > TABLE:
            shapes.clear()
        for w in set(words).difference(rows):
            a, z = core_span(w, 0)
            shape = w[a:z].translate(_SHAPE)
            # words of one shape without a digit differ in the word itself alone, the others in whether they look like keys
            own = w[a:z].lower() if "d" not in shape else ("#" if len(shape) >= 24 and _KEY.fullmatch(w, a, z) else "")
            key = (shape, own if own in self.words or own == "#" else "")
            if (row := shapes.get(key)) is None:
                ids = self._known(word_features(w))
                if (row := self.sets.get(ids)) is None:
                    row = self.sets[ids] = len(self.sets) + 1
                    if row == len(self.table):
                        self.table, self.most = (np.concatenate([x, np.zeros_like(x)]) for x in (self.table, self.most))
                    own_parts = self._sum(ids)
                    self.table[row], self.most[row] = own_parts, (own_parts[:, 1:] - own_parts[:, :1]).max(1)
                shapes[key] = row
            rows[w] = row
        return np.fromiter(map(rows.__getitem__, words), np.int64, len(words))

    def decode(self, segments: list[tuple[list[str], np.ndarray]]) -> list[np.ndarray]:
        """Viterbi labels of (words, which may be part of a span): every word is scored, and the best path is exact.

        A label other than O gains at most a bound over O at each word: the largest difference of its scores and of a step.
        Words of a bound that isn't positive can only lose; a span reaches past words of positive bound no further than
        until the loss outweighs all that the text could gain. Steps are summed up within these stretches alone.
        """
        if not any(w for w, _ in segments):
            return [np.zeros(0, np.int8) for _ in segments]
        sizes = np.array([len(w) for w, _ in segments])
        # two blanks (row 0) stand between texts, so that no text sees another's words
        start = 2 + np.concatenate([[0], np.cumsum(sizes + 2)[:-1]])
        ids = np.zeros(int(sizes.sum()) + 2 * len(sizes) + 2, np.int64)
        place = np.repeat(start - np.concatenate([[0], np.cumsum(sizes)[:-1]]), sizes) + np.arange(sizes.sum())
        ids[place] = self.numbers([w for words, _ in segments for w in words])
        may = np.concatenate([f for _, f in segments])
        still = self.step[:-1][0, 0]
        enter = np.maximum(self.step[:-1, 1:].max(0) - still, self.step[-1, 1:] - self.step[-1, 0])
        leave = max(0.0, float((self.step[1:-1, 0] - still).max()))
        bound = sum(self.most[ids[place + o], j] for j, o in enumerate(_OFFSETS)) + enter.max()
        bound[~may] = -1e4
        near = np.flatnonzero(bound > -leave)
        for lo in range(0, len(near), CELLS):
            some = near[lo : lo + CELLS]
            own = sum(self.table[ids[place[some] + o], j] for j, o in enumerate(_OFFSETS))
            bound[some] = np.where(may[some], (own[:, 1:] + enter).max(1) - own[:, 0], -1e4)
        ends = np.cumsum(sizes)
        stretches: list[tuple[int, int, int]] = []  # text, first word, after the last
        for k in np.unique(np.searchsorted(ends, np.flatnonzero(bound > -leave), side="right")):
            stretches += [(int(k), a, z) for a, z in _stretches(bound[ends[k] - sizes[k] : ends[k]], leave)]
        out = [np.zeros(n, np.int8) for n in sizes]
        stretches.sort(key=lambda s: s[2] - s[1])
        lo = 0
        while lo < len(stretches):
            hi = lo + 1
            while hi < len(stretches) and (hi + 1 - lo) * (stretches[hi][2] - stretches[hi][1] + 2) <= CELLS:
                hi += 1
            self._best(stretches[lo:hi], ids, may, start, sizes, out)
            lo = hi
        return out

    def _best(self, stretches, ids, may, start, sizes, out) -> None:
        """Writes the best labels of stretches, the words around which are O, into out."""
        text, first, after = np.array(stretches).T
        many, n = after - first, len(LABELS)
        most = int(many.max()) + 2
        emit = np.zeros((len(stretches), most, n))
        emit[:, :, 1:] = -1e4
        before = (first > 0).astype(int)  # a word before the stretch, which is O
        row = np.repeat(np.arange(len(stretches)), many)
        step = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many)
        at = (start[text] + first)[row] + step
        own = sum(self.table[ids[at + o], j] for j, o in enumerate(_OFFSETS))
        own[:, 1:] -= np.where(may[at - 2 - 2 * text[row]], 0, 1e4)[:, None]
        emit[row, before[row] + step] = own
        back = np.zeros((len(stretches), most, n), np.int8)
        best = emit[:, 0] + self.step[-1]
        length = before + many + (after < sizes[text])
        ends = np.zeros((len(stretches), n))
        ends[length == 1] = best[length == 1]
        for t in range(1, most):
            ways = best[:, :, None] + self.step[None, :-1]
            back[:, t] = ways.argmax(1)
            best = ways.max(1) + emit[:, t]
            ends[length == t + 1] = best[length == t + 1]
        path = np.zeros((len(stretches), most), np.int8)
        label = ends.argmax(1)
        for t in range(most - 1, -1, -1):
            inside = t < length
            path[inside, t] = label[inside]
            label = np.where(inside, back[np.arange(len(stretches)), t, label], label)
        for r, (k, a, z) in enumerate(stretches):
            out[k][a:z] = path[r, before[r] : before[r] + z - a]


def _stretches(bound: np.ndarray, leave: float) -> list[tuple[int, int]]:
    """(first, after last) of the stretches of a text that may hold spans: its live words, and as many others around them as a span could cross.

    A span over some words gains at most the sum of their bounds and leave. So it ends where the greatest sum up to a live
    word and the loss since are used up, begins likewise, and crosses from one live word to the next only if the greatest
    sum up to the one, the loss between them and the greatest sum from the other on come to more than nothing.
    """
    live = np.flatnonzero(bound > -leave)
    total, lost = (np.concatenate([[0], np.cumsum(x)]) for x in (bound, np.minimum(bound, 0)))
    upto = total[live + 1] - np.minimum.accumulate(total)[live] + leave
    onward = np.maximum.accumulate(total[::-1])[::-1][live + 1] - total[live] + leave
    after = np.searchsorted(-lost, -lost[live + 1] + upto, side="left")
    first = np.searchsorted(-lost, -lost[live] - onward, side="right") - 1
    crossed = upto[:-1] + lost[live[1:]] - lost[live[:-1] + 1] + onward[1:] - leave > 0
    after[:-1] = np.maximum(after[:-1], np.where(crossed, live[1:] + 1, 0))
    first, after = np.minimum.accumulate(np.maximum(first, 0)[::-1])[::-1], np.maximum.accumulate(np.minimum(after, len(bound)))
    new = np.flatnonzero(np.concatenate([[True], first[1:] > after[:-1]]))
    return list(zip(first[new].tolist(), after[[*(new[1:] - 1), len(live) - 1]].tolist(), strict=True))


def _posteriors(emit: np.ndarray, step: np.ndarray, real: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Label probabilities of every cell, and expected label steps (the last row: first labels), by forward and backward sums."""
    rows, most, n = emit.shape
    fold = lambda x, axis: (m := x.max(axis, keepdims=True)).squeeze(axis) + np.log(np.exp(x - m).sum(axis))
    ahead, behind = np.zeros_like(emit), np.zeros_like(emit)
    ahead[:, 0] = emit[:, 0] + step[-1]
    for t in range(1, most):
        new = fold(ahead[:, t - 1, :, None] + step[None, :-1], 1) + emit[:, t]
        ahead[:, t] = np.where(real[:, t, None], new, ahead[:, t - 1])
    for t in range(most - 2, -1, -1):
        new = fold(step[None, :-1] + (emit[:, t + 1] + behind[:, t + 1])[:, None, :], 2)
        behind[:, t] = np.where(real[:, t + 1, None], new, behind[:, t + 1])
    total = fold(ahead[:, -1], 1)
    post = np.exp(ahead + behind - total[:, None, None])
    steps = np.zeros((n + 1, n))
    steps[-1] = post[:, 0].sum(0)
    for t in range(1, most):
        live = real[:, t]
        joint = ahead[live, t - 1, :, None] + step[None, :-1] + (emit[live, t] + behind[live, t])[:, None, :] - total[live, None, None]
        steps[:-1] += np.exp(joint).sum(0)
    return post, steps


def field_spans(texts: list[str], field: ChainField) -> list[list[tuple[int, int, str]]]:
    """Spans that the field labels in each text: every word of every text is decoded."""
    out, lo = [], 0
    while lo < len(texts):
        hi, size = lo + 1, len(texts[lo])
        while hi < len(texts) and size + len(texts[hi]) <= HELD:
            size += len(texts[hi])
            hi += 1
        some, lo = texts[lo:hi], hi
        words = [_CHUNK.findall(t) for t in some]
        out += [_spans(t, path) for t, path in zip(some, field.decode([(w, np.ones(len(w), bool)) for w in words]), strict=True)]
    return out


def _spans(text: str, path: np.ndarray) -> list[tuple[int, int, str]]:
    spans: list = []
    if path.any():
        own = None
        for m, y in zip(_CHUNK.finditer(text), path, strict=True):
            label = LABELS[y]
            if label[0] == "I" and own:
                own = (own[0], core_span(m.group(), m.start())[1], own[2])
                spans[-1] = own
            elif label != "O":
                own = (*core_span(m.group(), m.start()), label[2:])
                spans.append(own)
            else:
                own = None
    return [s for s in spans if s[0] < s[1]]


def all_spans(texts: list[str], field: ChainField) -> list[tuple[list, list]]:
    """Base spans of each text, and all: those of the field that touch no base span are added."""
    out = []
    for text, more in zip(texts, field_spans(texts, field), strict=True):
        base = base_spans(text)
        added = [s for s in more if not any(s[0] < b[1] and b[0] < s[1] for b in base)]
        out.append((base, sorted([*base, *added], key=lambda s: (s[0], KINDS.index(s[2])))))
    return out


def show(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{z}" for a, z, k in spans)


def train_field(spark: SparkSession, **options) -> ChainField:
    return ChainField.train([(r["words"], r["labels"]) for r in labelled_examples(spark, **options).collect()])


def find_personal_data(docs: DataFrame, field: ChainField) -> DataFrame:
    """doc_id, numbers of base spans by kind, base_sha256, spans and their number, of every row from its whole text; null is empty; no shuffle."""
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def run(batch):
        texts, rows = texts_of(batch), []
        for lo in range(0, len(texts), 2000):
            rows += all_spans(texts[lo : lo + 2000], field)
        counts = {f"n_{k}": [sum(s[2] == k for s in base) for base, _ in rows] for k in BASE_KINDS}
        return {"doc_id": batch.column("doc_id"), **counts, "base_sha256": [hashlib.sha256(show(b).encode()).hexdigest() for b, _ in rows], "spans": [show(s) for _, s in rows], "n_spans": [len(s) for _, s in rows]}

    return map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, {', '.join(f'n_{k} bigint' for k in BASE_KINDS)}, base_sha256 string, spans string, n_spans bigint")


def redact(docs: DataFrame, field: ChainField) -> DataFrame:
    """docs with every span of its text replaced by its kind in angle brackets; other columns stay."""

    def run(batches):
        for batch in batches:
            texts = batch.column("text").to_pylist()
            for k, (_, spans) in enumerate(all_spans([t or "" for t in texts], field)):
                end = len(texts[k]) if spans else 0
                for a, z, kind in reversed(spans):
                    if z <= end:
                        texts[k], end = f"{texts[k][:a]}<{kind}>{texts[k][z:]}", a
            yield batch.set_column(batch.schema.get_field_index("text"), batch.schema.field("text"), pa.array(texts, batch.schema.field("text").type))

    return docs.mapInArrow(run, docs.schema)


def base_counts(docs: DataFrame) -> DataFrame:
    """doc_id and the numbers of base spans of every row, by the fixed patterns alone; null is empty."""
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def run(batch):
        found = [[s[2] for s in base_spans(t)] for t in texts_of(batch)]
        return {"doc_id": batch.column("doc_id")} | {f"n_{k}": [f.count(k) for f in found] for k in BASE_KINDS}

    return map_arrow(docs.select("doc_id", "text"), run, f"doc_id {kind}, {', '.join(f'n_{k} bigint' for k in BASE_KINDS)}")


#: The same in DuckDB, over the view documents.
COUNTS_SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
x AS (SELECT doc_id, len(regexp_extract_all(t, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+')) AS n_email,
  regexp_extract_all(t, '[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)') AS ips,
  list_transform(regexp_extract_all(t, '[0-9]([\x20-]?[0-9])+'), lambda c: reverse(regexp_replace(c, '[^0-9]', '', 'g'))) AS cards,
  list_transform(regexp_extract_all(t, '\+[0-9][\x20().0-9-]+[0-9]'), lambda c: len(regexp_replace(c, '[^0-9]', '', 'g'))) AS phones FROM d)
SELECT doc_id, n_email::BIGINT AS n_email,
  len(list_filter(ips, lambda i: list_max(list_transform(string_split(i, '.'), lambda p: p::HUGEINT)) <= 255))::BIGINT AS n_ip,
  len(list_filter(cards, lambda c: len(c) BETWEEN 14 AND 19 AND list_sum(list_transform(range(1, len(c) + 1), lambda k:
    c[k]::INT * (2 - k % 2) - CASE WHEN k % 2 = 0 AND c[k]::INT > 4 THEN 9 ELSE 0 END)) % 10 = 0))::BIGINT AS n_card,
  len(list_filter(phones, lambda n: n BETWEEN 10 AND 15))::BIGINT AS n_phone FROM x
"""
