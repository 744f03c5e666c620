"""Quality classifier by positive-unlabelled learning with the non-negative risk.

Trusted positives are rows labelled 1, the unlabelled set is web text without a label; negatives are never used. The class prior of the
unlabelled text is estimated by the best-bin rule: with a plain positive-vs-unlabelled score, the least ratio of unlabelled to positive mass
above a threshold bounds the prior from above. Then a small network minimises

    prior * E_p[l(g)] + max(0, E_u[l(-g)] - prior * E_p[l(-g)])

with the logistic loss; where the second term turns negative its gradient is reversed, as it can only fall below zero by overfitting.

Features are numbers of the whole text (kinds of characters, words, lines and their repetition), computed once for all documents and kept as a table; the
network is fitted on a bounded sample of `bound` positives and as many unlabelled rows (a documented limit), and applied to every row.
"""

from __future__ import annotations

import math
import operator
from collections import Counter
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import list_array, over_slices

BOUND = 8192
#: Kinds of ASCII characters that are counted one by one.
SIGNS = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~\n\t"
NAMES = (
    "log_chars", "log_words", "lower", "upper", "digits", "blanks", "other", "word_length", "word_spread", "distinct_words", "top_word", "repeated", "distinct_lines",
    "line_words", "longest_word", "sentence_words", "capital_words", "sign_words", "run",
)
WIDTH = len(NAMES) + len(SIGNS) + 1
_KIND = np.zeros(256, np.int64)
_KIND[65:91], _KIND[97:123], _KIND[48:58], _KIND[32], _KIND[128:] = 1, 2, 3, 4, 5
for _i, _c in enumerate(SIGNS):
    _KIND[ord(_c)] = 6 + _i


def features(text: str | None) -> np.ndarray:
    """Numbers of one whole text; null and empty texts give zeros."""
    out = np.zeros(WIDTH, np.float32)
    raw = (text or "").encode("utf-8", "surrogatepass")
    if not raw:
        return out
    b = np.frombuffer(raw, np.uint8)
    kinds = np.bincount(_KIND[b], minlength=6 + len(SIGNS))
    words = raw.split()
    n = len(words)
    lengths = np.fromiter(map(len, words), np.int64, n) if n else np.zeros(1, np.int64)
    counts = Counter(words)
    lines = [x for x in raw.split(b"\n") if x]
    letters = max(1, kinds[1] + kinds[2])
    stops = kinds[6 + SIGNS.index(".")] + kinds[6 + SIGNS.index("!")] + kinds[6 + SIGNS.index("?")]
    same = np.diff(np.flatnonzero(np.concatenate(([True], b[1:] != b[:-1], [True]))))
    out[: len(NAMES)] = (
        math.log1p(len(raw)), math.log1p(n), kinds[2] / len(raw), kinds[1] / letters, kinds[3] / len(raw), kinds[4] / len(raw), kinds[5] / len(raw), lengths.mean(), lengths.std(),
        len(counts) / max(1, n), max(counts.values(), default=0) / max(1, n), math.sqrt(sum(map(operator.eq, words, words[1:])) / max(1, n)), len(set(lines)) / max(1, len(lines)), math.log1p(n / max(1, len(lines))),
        math.log1p(lengths.max()), math.log1p(n / (1 + stops)), sum(w[:1].isupper() for w in words) / max(1, n), sum(not w[-1:].isalnum() and w[-1] < 128 for w in words) / max(1, n), math.log1p(same.max()),
    )
    out[len(NAMES) : -1] = np.sqrt(kinds[6:] / len(raw))
    return out


def feature_table(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, features array<float>; one row per row of `docs`, repeats and null ids included. An empty table gives no rows. A long text is one slice."""

    def work(part: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([part.column("id"), list_array([features(t) for t in part.column("text").to_pylist()], pa.float32())], ["id", "features"])

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(over_slices(work), f"id {docs.schema[id_col].dataType.simpleString()}, features array<float>").withColumnRenamed("id", id_col)


@dataclass
class Network:
    """One hidden layer of tanh units on standardised features."""

    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float

    def inputs(self, x: np.ndarray) -> np.ndarray:
        return np.clip((x - self.mean) / self.scale, -8, 8)

    def margin(self, x: np.ndarray) -> np.ndarray:
        return np.tanh(self.inputs(x) @ self.w1 + self.b1) @ self.w2 + self.b2

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.margin(x), -40, 40)))


def _fit(p: np.ndarray, u: np.ndarray, slope, hidden: int, steps: int, seed: int) -> Network:
    """Adam on random batches; slope(margin_p, margin_u) gives the risk's derivative by each margin."""
    rng = np.random.default_rng(seed)
    every = np.vstack([p, u])
    net = Network(every.mean(0), every.std(0) + 1e-3, rng.normal(0, 1 / math.sqrt(p.shape[1]), (p.shape[1], hidden)), np.zeros(hidden), rng.normal(0, 1 / math.sqrt(hidden), hidden), 0.0)
    zp, zu = net.inputs(p), net.inputs(u)
    weights = [net.w1, net.b1, net.w2, np.zeros(1)]
    first, second = [np.zeros_like(w) for w in weights], [np.zeros_like(w) for w in weights]
    for step in range(1, steps + 1):
        xp, xu = zp[rng.integers(0, len(zp), 512)], zu[rng.integers(0, len(zu), 512)]
        x = np.vstack([xp, xu])
        h = np.tanh(x @ weights[0] + weights[1])
        g = h @ weights[2] + weights[3][0]
        d = np.concatenate(slope(g[:512], g[512:]))
        back = np.outer(d, weights[2]) * (1 - h * h)
        grads = [x.T @ back + 1e-4 * weights[0], back.sum(0), h.T @ d + 1e-4 * weights[2], np.array([d.sum()])]
        rate = 0.01 * (1 - step / (steps + 1))
        for i, gr in enumerate(grads):
            first[i] = 0.9 * first[i] + 0.1 * gr
            second[i] = 0.999 * second[i] + 0.001 * gr * gr
            weights[i] = weights[i] - rate * (first[i] / (1 - 0.9**step)) / (np.sqrt(second[i] / (1 - 0.999**step)) + 1e-8)
    net.w1, net.b1, net.w2, net.b2 = *weights[:3], float(weights[3][0])
    return net


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def best_bin_prior(score_p: np.ndarray, score_u: np.ndarray, delta: float = 0.1) -> float:
    """Least upper bound on the positive share of U over thresholds, with Hoeffding widths against thin bins."""
    cuts = np.quantile(score_p, np.linspace(0.01, 0.95, 95))
    q_p, q_u = (score_p[None] >= cuts[:, None]).mean(1), (score_u[None] >= cuts[:, None]).mean(1)
    width = math.sqrt(math.log(4 / delta) / (2 * len(score_u))) + math.sqrt(math.log(4 / delta) / (2 * len(score_p)))
    best = int(np.argmin((q_u + width) / q_p))
    return float(np.clip(q_u[best] / q_p[best], 0.01, 0.99))


def fit_pu(p: np.ndarray, u: np.ndarray, hidden: int = 24, steps: int = 2500, prior: float | None = None, beta: float = 0.01, seed: int = 11) -> tuple[Network, float]:
    """The network and the class prior. Without positives or unlabelled rows: a constant score of one half."""
    if not len(p) or not len(u):
        return Network(np.zeros(WIDTH), np.ones(WIDTH), np.zeros((WIDTH, 1)), np.zeros(1), np.zeros(1), 0.0), 0.5
    if prior is None:
        half_p, half_u = len(p) // 2 or 1, len(u) // 2 or 1
        plain = _fit(p[:half_p], u[:half_u], lambda gp, gu: (-_sigmoid(-gp) / len(gp), _sigmoid(gu) / len(gu)), hidden, steps // 3, seed)
        prior = best_bin_prior(plain.margin(p[half_p:] if len(p) > 1 else p), plain.margin(u[half_u:] if len(u) > 1 else u))

    def slope(gp: np.ndarray, gu: np.ndarray):
        negative = np.logaddexp(0, gu).mean() - prior * np.logaddexp(0, gp).mean()
        of_p, of_u = -prior * _sigmoid(gp) / len(gp), _sigmoid(gu) / len(gu)
        if negative < -beta:  # reversed: the clipped part may only rise
            return -of_p, -of_u
        return of_p - prior * _sigmoid(-gp) / len(gp), of_u

    net = _fit(p, u, slope, hidden, steps, seed)
    # the reversed steps leave negatives near a margin of zero; where even the lowest trusted positives stand clear of it, the
    # zero moves up to one below them, and never down
    net.b2 -= max(0.0, float(np.quantile(net.margin(p), 0.002)) - 1.0)
    return net, prior


def _bounded(rows: DataFrame, id_col: str, bound: int) -> np.ndarray:
    """At most `bound` feature rows, by least hash of the id: the same rows in every run.

    A cut on the hash, set by the count, comes before the ordering, so that tasks send about `bound` rows together and not each.
    """
    n = rows.count()
    if n > 2 * bound:
        rows = rows.where(F.xxhash64(id_col) < int((2 * bound / n) * 2**64) - 2**63)
    got = rows.orderBy(F.xxhash64(id_col), id_col).limit(bound).select("features").toPandas()["features"]
    return np.vstack(got.to_list()).astype(np.float64) if len(got) else np.empty((0, WIDTH))


def train(table: DataFrame, labels: DataFrame, id_col: str = "doc_id", label_col: str = "quality", bound: int = BOUND) -> tuple[Network, float]:
    """`table` (id, features) of the rows to learn from; `labels` of those rows. Null labels and ids count as no label; an id with several labels
    is positive if all of them are 1."""
    known = labels.where(f"{label_col} IS NOT NULL").groupBy(id_col).agg(F.min(label_col).alias("_label"))
    joined = table.join(known, id_col, "left")
    return fit_pu(_bounded(joined.where("_label = 1"), id_col, bound), _bounded(joined.where("_label IS NULL"), id_col, bound))


def score(table: DataFrame, network: Network, threshold: float = 0.3) -> DataFrame:
    """Adds score (0 to 1) and predicted (1 from the threshold on), replacing the features."""
    shared = table.sparkSession.sparkContext.broadcast(network)

    @F.pandas_udf("double")
    def probability(x: pd.Series) -> pd.Series:
        return pd.Series(shared.value.probability(np.vstack(x.to_list()).astype(np.float64)) if len(x) else [], dtype="float64")

    scored = table.withColumn("score", probability("features")).drop("features")
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
