"""Language identification by rank-order profiles of character n-grams and their out-of-place distance."""

from __future__ import annotations

import functools
import sys
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import held_out, map_arrow, texts_of

#: n-grams of one to LONGEST letters; ranks kept of a language and of a document.
LONGEST = 3
PROFILE = 400
_BITS = 21
#: What stands for a blank in codes: no letter, and not 0, so that a leading blank makes another code.
_BLANK = 1


@functools.cache
def _classes() -> np.ndarray:
    """For each code point 1 if it is a letter (Unicode category L), 2 if a mark (M, as vowel signs inside words), else 0."""
    kinds = {"L": 1, "M": 2}
    return np.fromiter((kinds.get(unicodedata.category(chr(c))[0], 0) for c in range(sys.maxunicode + 1)), np.uint8, sys.maxunicode + 1)


def gram_counts(text: str, longest: int = LONGEST) -> tuple[np.ndarray, np.ndarray]:
    """Codes and counts of the n-grams of the words of a text (lower-cased runs of letters and marks with a blank on each side).

    A code packs up to three code points of 21 bits; blanks are 1, and runs of other characters are one blank.
    """
    points = np.frombuffer(f" {text.lower()} ".encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    kinds = _classes()[points]
    if not (kinds == 1).any():
        return np.empty(0, np.int64), np.empty(0, np.int64)
    points[kinds == 0] = _BLANK
    points = points[(points > _BLANK) | np.concatenate([[True], points[:-1] > _BLANK])]
    codes, gram = [points[points > _BLANK]], points
    for n in range(2, longest + 1):
        # A gram holds at most one blank, at an end, and never a blank between letters.
        gram = (gram[:-1] << _BITS) | points[n - 1 :]
        inside = np.ones(len(gram), bool)
        for k in range(1, n - 1):
            inside &= points[k : k + len(gram)] > _BLANK
        codes.append(gram[inside])
    return np.unique(np.concatenate(codes), return_counts=True)


def ranked(codes: np.ndarray, counts: np.ndarray, most: int = PROFILE) -> np.ndarray:
    """The most frequent codes in order of falling count, ties by code."""
    order = np.lexsort((codes, -counts))[:most]
    return codes[order]


def learn_profiles(docs: DataFrame, most: int = PROFILE, longest: int = LONGEST) -> dict[str, np.ndarray]:
    """Ranked codes of each language from all rows with a lang that are not held out.

    Counts are added up over all rows (partial sums in each batch, then a grouped sum); only the first most ranks
    of each language come to the driver: the model, which grows with the values of lang and with nothing else.
    """

    def count(batch):
        per: dict[str, list] = {}
        for lang, text in zip(batch.column("lang").to_pylist(), texts_of(batch), strict=True):
            per.setdefault(lang, []).append(gram_counts(text, longest))
        langs, codes, sums = [], [], []
        for lang, found in per.items():
            c, at = np.unique(np.concatenate([x[0] for x in found]), return_inverse=True)
            n = np.bincount(at, np.concatenate([x[1] for x in found]), len(c)).astype(np.int64) if len(c) else np.empty(0, np.int64)
            langs.append(np.full(len(c), len(sums)))
            codes.append(c)
            sums.append(n)
        names = list(per)
        return {"lang": pa.array([names[i] for i in np.concatenate(langs)] if langs else [], pa.string()), "code": pa.array(np.concatenate(codes)), "n": pa.array(np.concatenate(sums))}

    rows = docs.where(F.col("lang").isNotNull() & ~held_out(F.col("doc_id"))).select("lang", "text")
    counts = map_arrow(rows, count, "lang string, code bigint, n bigint").groupBy("lang", "code").agg(F.sum("n").alias("n"))
    rank = F.row_number().over(Window.partitionBy("lang").orderBy(F.col("n").desc(), "code"))
    top = counts.withColumn("rank", rank).where(F.col("rank") <= most)
    lists = top.groupBy("lang").agg(F.array_sort(F.collect_list(F.struct("rank", "code"))).alias("p")).collect()
    return {r["lang"]: np.array([x["code"] for x in r["p"]], np.int64) for r in sorted(lists, key=lambda r: r["lang"])}


class Ranker:
    """Out-of-place distances of a document's ranks to every profile."""

    def __init__(self, profiles: dict[str, np.ndarray], most: int = PROFILE):
        self.langs, self.most = list(profiles), most
        self.codes = np.unique(np.concatenate(list(profiles.values()))) if profiles else np.empty(0, np.int64)
        # rank of each known code in each language; most where a profile lacks it
        self.ranks = np.full((len(self.codes) + 1, len(self.langs)), most, np.int64)
        for k, lang in enumerate(self.langs):
            self.ranks[np.searchsorted(self.codes, profiles[lang]), k] = np.arange(len(profiles[lang]))

    def distances(self, text: str) -> np.ndarray | None:
        """Sum over the document's ranks of the distance of ranks, most for n-grams outside a profile, as a share of the worst."""
        codes, counts = gram_counts(text)
        if not len(codes):
            return None
        own = ranked(codes, counts, self.most)
        at = np.searchsorted(self.codes, own)
        at[(at == len(self.codes)) | (self.codes[np.minimum(at, max(len(self.codes) - 1, 0))] != own)] = len(self.codes)
        known = self.ranks[at]
        out = np.where(known < self.most, np.abs(known - np.arange(len(own))[:, None]), self.most)
        return out.sum(0) / (self.most * len(own))

    def predict(self, text: str) -> tuple[str, float]:
        if not self.langs or (d := self.distances(text)) is None:
            return "und", 0.0
        best = int(np.argmin(d))
        return self.langs[best], float(1 - d[best])


def identify(docs: DataFrame, profiles: dict[str, np.ndarray]) -> DataFrame:
    """doc_id, held_out, lang_pred and score (1 less the relative distance) of every row.

    Null texts and texts without a letter get und and 0, as does everything where nothing was learned; equal
    distances go to the first language in code point order. Whole texts are read; no shuffle.
    """
    ranker = Ranker(profiles)
    kind = next(f.dataType for f in docs.schema if f.name == "doc_id").simpleString()

    def score(batch):
        found = [ranker.predict(t) for t in texts_of(batch)]
        return {"doc_id": batch.column("doc_id"), "held_out": batch.column("held_out"), "lang_pred": [x[0] for x in found], "score": [x[1] for x in found]}

    return map_arrow(docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text"), score, f"doc_id {kind}, held_out boolean, lang_pred string, score double")


assert sys.maxunicode < 1 << _BITS
