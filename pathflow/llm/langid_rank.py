"""Language ID by rank-order profiles.

Training counts character n-grams (1 to 3 letters, words joined by one blank) of each language over *all* training documents:
numpy counts per task, Spark sums. Each language keeps its most frequent n-grams in order. A document's own most frequent n-grams are
compared by out-of-place distance; an n-gram that a profile lacks costs the profile's length. Profiles are bounded: languages * profile length.

Null texts and texts without a letter are `und` and teach nothing; null languages teach nothing. Rows that repeat count, and are answered, each; ties in
frequency go by n-gram code, ties in distance by language name. Empty training tables give no profiles, with which every text is `und`. Long texts are
counted in windows of a million characters, so a worker's memory follows the kinds of n-grams.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import give_back, over_slices, slices

PROFILE, DEPTH = 400, 400
_LETTERS: np.ndarray | None = None
BLANK = 32


def _letters() -> np.ndarray:
    """Code point -> itself if a letter, else 0; made once per worker."""
    global _LETTERS
    if _LETTERS is None:
        _LETTERS = np.fromiter((c if chr(c).isalpha() else 0 for c in range(0x110000)), np.int64, 0x110000)
    return _LETTERS


def ngrams(text: str | None) -> np.ndarray:
    """Codes of all 1- to 3-grams: lower-cased letters, other runs as one blank; empty without a letter."""
    if not text:
        return np.empty(0, np.int64)
    c = _letters()[np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)]
    c = np.concatenate(([0], c, [0]))
    keep = np.ones(len(c), bool)
    keep[1:] = (c[1:] != 0) | (c[:-1] != 0)
    c = c[keep]
    if len(c) < 2:
        return np.empty(0, np.int64)
    c[c == 0] = BLANK
    two = (c[:-1] << 21) | c[1:]
    return np.concatenate((c[c != BLANK], two, (two[:-1] << 21) | c[2:]))


Tally = tuple[np.ndarray, np.ndarray]  # n-grams in code order, and their counts
NONE: Tally = (np.empty(0, np.int64), np.empty(0, np.int64))


def merged(a: Tally, b: Tally) -> Tally:
    if not len(a[0]):
        return b
    grams, place = np.unique(np.concatenate((a[0], b[0])), return_inverse=True)
    return grams, np.bincount(place, np.concatenate((a[1], b[1])), len(grams)).astype(np.int64)


def tally(text: str | None, window: int = 1 << 20) -> Tally:
    """Counts of a text's n-grams. A longer text goes by windows that end behind a character which is no letter: only the n-gram from the last letter
    over the blank to the next letter crosses such a border, and is added."""
    if text is None or len(text) <= window:
        return np.unique(ngrams(text), return_counts=True)
    out, at, last = NONE, 0, ""
    while at < len(text):
        stop = min(len(text), at + window)
        while stop < len(text) and text[stop - 1].isalpha():
            stop += 1
        part, at = text[at:stop], stop
        out = merged(out, np.unique(ngrams(part), return_counts=True))
        first = next(filter(str.isalpha, part), "")
        if last and first:
            # blank a, a blank b, b blank: the codes of three end the list
            out = merged(out, (ngrams(f"{last} {first}")[-2:-1], np.ones(1, np.int64)))
        last = next(filter(str.isalpha, reversed(part)), last)
    return out


def ranked(counted: Tally, depth: int) -> np.ndarray:
    """The most frequent n-grams in order; ties by code."""
    # a stable order by falling count keeps codes ascending within ties
    return counted[0][np.argsort(-counted[1], kind="stable")[:depth]]


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of a whole task, merged slice by slice: memory follows the kinds of n-grams, not the texts."""
    held: dict[str, Tally] = {}
    for batch in batches:
        for part in slices(batch, 1 << 20):
            texts: dict[str, list[str]] = {}
            for lang, text in zip(part.column("lang").to_pylist(), part.column("text").to_pylist(), strict=True):
                if text:
                    texts.setdefault(lang, []).append(text)
            for lang, own in texts.items():
                held[lang] = merged(held.get(lang, NONE), np.unique(np.concatenate([ngrams(t) for t in own]), return_counts=True) if len(own) > 1 else tally(own[0]))
    for lang, (grams, counts) in held.items():
        yield pa.RecordBatch.from_arrays([pa.array([lang] * len(grams), pa.string()), pa.array(grams, pa.int64()), pa.array(counts, pa.int64())], ["lang", "gram", "n"])
    held.clear()
    give_back()


def language_profiles(train: DataFrame, text_col: str = "text", lang_col: str = "lang", profile: int = PROFILE) -> dict[str, np.ndarray]:
    """Profiles of the non-null languages; learned languages without any letter get none and are never predicted."""
    rows = train.select(F.col(text_col).alias("text"), F.col(lang_col).alias("lang")).where("lang IS NOT NULL")
    counts = rows.mapInArrow(_count, "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    place = F.row_number().over(W.partitionBy("lang").orderBy(F.desc("n"), "gram"))
    top = counts.withColumn("place", place).where(F.col("place") <= profile).orderBy("lang", "place").collect()
    out: dict[str, list[int]] = {}
    for r in top:
        out.setdefault(r["lang"], []).append(r["gram"])
    return {lang: np.array(g, np.int64) for lang, g in out.items()}


class RankOrder:
    """Profiles as one sorted table of n-grams with a row of ranks for each."""

    def __init__(self, profiles: dict[str, np.ndarray], depth: int = DEPTH):
        self.langs, self.depth = sorted(profiles), depth
        self.length = max([1, *(len(p) for p in profiles.values())])
        self.grams = np.unique(np.concatenate([np.empty(0, np.int64), *profiles.values()]))
        self.ranks = np.full((len(self.grams) + 1, len(self.langs)), -1, np.int64)  # the last row: in no profile
        for i, lang in enumerate(self.langs):
            self.ranks[np.searchsorted(self.grams, profiles[lang]), i] = np.arange(len(profiles[lang]))

    def predict(self, text: str | None) -> tuple[str, float, float]:
        """Language, score (1 - distance / greatest distance), and the gap to the runner-up as a share."""
        counted = tally(text)
        if not len(counted[0]) or not self.langs:
            return "und", 0.0, 0.0
        own = ranked(counted, self.depth)
        at = np.searchsorted(self.grams, own)
        at[(at == len(self.grams)) | (self.grams[np.minimum(at, len(self.grams) - 1)] != own)] = len(self.grams)
        ranks = self.ranks[at]
        away = np.where(ranks < 0, self.length, np.minimum(np.abs(ranks - np.arange(len(own))[:, None]), self.length)).sum(0)
        order = np.argsort(away, kind="stable")
        best = away[order[0]]
        gap = (away[order[1]] - best) / max(1, away[order[1]]) if len(order) > 1 else 1.0
        return self.langs[order[0]], float(1 - best / (self.length * len(own))), float(gap)


def identify(docs: DataFrame, profiles: dict[str, np.ndarray], text_col: str = "text", keep: list[str] | None = None, depth: int = DEPTH, names: tuple[str, str, str] = ("lang_pred", "score", "gap")) -> DataFrame:
    """`keep` columns with lang_pred ('und' for null texts and texts without a letter), score in 0 to 1, gap in 0 to 1.

    `names` are the added columns' names; columns of these names are replaced.
    """
    keep = [c for c in (docs.columns if keep is None else keep) if c not in names]
    model = docs.sparkSession.sparkContext.broadcast(profiles)
    rows = docs.select(*[F.col(c).alias(f"c{i}") for i, c in enumerate(keep)], F.col(text_col).alias("text"))
    kinds = rows.select(*rows.columns[:-1])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ranker = RankOrder(model.value, depth)

        def work(part: pa.RecordBatch) -> pa.RecordBatch:
            found = [ranker.predict(t) for t in part.column("text").to_pylist()]
            answers = [pa.array([f[i] for f in found], t) for i, t in enumerate((pa.string(), pa.float64(), pa.float64()))]
            return pa.RecordBatch.from_arrays([*part.columns[:-1], *answers], [*part.schema.names[:-1], "lang_pred", "score", "gap"])

        yield from over_slices(work)(batches)

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in kinds.schema)
    out = rows.mapInArrow(run, ", ".join(x for x in (schema, "lang_pred string, score double, gap double") if x))
    return out.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(keep)], *[F.col(c).alias(n) for c, n in zip(("lang_pred", "score", "gap"), names, strict=True)])
