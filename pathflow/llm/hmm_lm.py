"""Hidden Markov language model: distributed Baum-Welch, scaled forward recursion.

Symbols. The `frequent` most frequent tokens (32,768 at most, a bound on what is broadcast) are symbols of their own; every
other token belongs to one of 256 rare classes, told by its last letters. A rare token's probability is that of its class in the HMM
times (c + 1) / (n + v + 1) within the class, where c counts over the whole corpus, n and v are the class's tokens and kinds,
and the last 1 is the share of all unseen tokens. So every text has an exact, normalised probability.

Training. Token counts are summed over all training documents. A few EM steps on a bounded sample (`sample` distinct texts of `longest` characters
at most) only break the symmetry of the states; then `passes` full Baum-Welch passes run over *all* training documents, whatever their length: expected
counts per task, summed by Spark by symbol; only the model itself (states * symbols) reaches the driver.

Scoring. One pass computes the forward likelihood of each whole text and its rare tokens; these meet the corpus counts in a shuffled
join on the token hash, never in a broadcast.

Null and empty texts are an end token alone. Rows that repeat count, and are scored, each. Empty training tables give a uniform model; empty tables to
score no rows. Workers hold one slice of texts (8 MB, or one longer text) and about 300 bytes a token of 150,000 tokens (or of one longer text).
Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cutoff, list_array, materialize, over_slices, slices

CLASSES, LOW = 256, (1 << 56) - 1
END = 1  # the end token's code: class 0, reserved


def _mix(x: np.ndarray) -> np.ndarray:
    """The finaliser of splitmix64."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


#: ASCII white space, and what is stripped from a word's end before its class is told.
SPACE = np.isin(np.arange(256), list(b"\t\n\v\f\r "))
STRIPPED = np.isin(np.arange(256), list(b".,;:!?\"')"))
_BYTE = np.where(SPACE, 0, _mix(np.arange(256, dtype=np.uint64) + np.uint64(0x9E3779B97F4A7C15)))
_LOWER = np.frombuffer(bytes(range(256)).lower(), np.uint8)


def _window_codes(b: np.ndarray, begins: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Codes of the words in the lower-cased bytes `b`, and where they start; a word also starts at each of `begins`.

    A word's hash is the sum over its bytes of a number of the byte times an odd number of its place, mixed with its length; its class (8 bits)
    is a hash of the last three bytes before closing punctuation.
    """
    solid = ~SPACE[b]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    first[begins] = solid[begins]
    starts = np.flatnonzero(first)
    if not len(starts):
        return np.empty(0, np.int64), starts
    at = np.arange(len(b), dtype=np.int32)
    place = at - np.maximum.accumulate(np.where(first, at, 0))
    place[~solid] = 0
    odd = _mix(np.arange(int(place.max()) + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
    sums = np.add.reduceat(_BYTE[b] * odd[place], starts)
    lengths = np.add.reduceat(solid, starts, dtype=np.int64)
    x = _mix(sums + lengths.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15))
    kept = np.maximum.accumulate(np.where(solid & ~STRIPPED[b], at, -1))[starts + lengths - 1].astype(np.int64)
    tail = np.zeros(len(starts), np.uint64)
    for i in range(3):
        near = kept - i
        inside = near >= starts
        tail = tail << np.uint64(8) | np.where(inside, b[np.maximum(near, 0)], 0).astype(np.uint64)
    return ((_mix(tail) & np.uint64(255)) << np.uint64(56) | (x & np.uint64(LOW)) | np.uint64(2)).view(np.int64), starts


def token_arrays(text: pa.Array, window: int = 1 << 20) -> list[np.ndarray]:
    """Token codes of every text (null: empty): its words, then one end. Bytes go by windows of about `window` that end in white space, so memory beside the codes is
    that of a window (some 40 bytes a byte), or of a longer word."""
    text = text.cast(pa.large_string()).fill_null("")
    offsets = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
    data = np.frombuffer(text.buffers()[2] or b"", np.uint8)[offsets[0] : offsets[-1]]
    offsets = offsets - offsets[0]
    begins = np.unique(offsets[:-1][np.diff(offsets) > 0])
    codes, starts, at = [np.empty(0, np.int64)], [np.empty(0, np.int64)], 0
    while at < len(data):
        stop = min(len(data), at + window)
        while stop < len(data):  # to the next white space
            gaps = np.flatnonzero(SPACE[data[stop : stop + window]])
            if len(gaps):
                stop += int(gaps[0]) + 1
                break
            stop = min(len(data), stop + window)
        lo, hi = np.searchsorted(begins, (at, stop))
        c, w = _window_codes(_LOWER[data[at:stop]], begins[lo:hi] - at)
        codes.append(c)
        starts.append(w + at)
        at = stop
    flat, place = np.concatenate(codes), np.concatenate(starts)
    cuts = np.searchsorted(place, offsets[1:-1]) if len(text) > 1 else []
    return [np.append(c, END) for c in np.split(flat, cuts)] if len(text) else []


def token_codes(text: str | None) -> np.ndarray:
    """word codes of one text and its end: class (8 bits), 55 bits of a hash and a set bit that keeps codes off END; as signed 64-bit."""
    return token_arrays(pa.array([text], pa.string()))[0]


def class_of(codes: np.ndarray) -> np.ndarray:
    return (codes.view(np.uint64) >> np.uint64(56)).astype(np.int64)


@dataclass
class Symbols:
    codes: np.ndarray  # frequent token codes, ascending
    counts: np.ndarray

    @property
    def size(self) -> int:
        return len(self.codes) + CLASSES

    def of(self, codes: np.ndarray) -> np.ndarray:
        """Symbol of each code; rare ones are at len(self.codes) + class."""
        n = len(self.codes)
        if not n:
            return class_of(codes)
        at = np.minimum(np.searchsorted(self.codes, codes), n - 1)
        return np.where(self.codes[at] == codes, at, n + class_of(codes))


@dataclass
class Model:
    start: np.ndarray  # (K,)
    moves: np.ndarray  # (K, K)
    emits: np.ndarray  # (symbols, K): p(symbol | state)


def _groups(lengths: np.ndarray, tokens: int) -> Iterator[np.ndarray]:
    """Documents in falling length, in groups of about so many tokens."""
    order = np.argsort(-lengths, kind="stable")
    part = np.cumsum(lengths[order]) // tokens
    for g in np.split(order, np.flatnonzero(np.diff(part)) + 1) if len(order) else ():
        yield g


def _time_major(docs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Symbols of documents in falling length, laid out by time; and where each time step begins."""
    lengths = np.array([len(d) for d in docs])
    flat = np.concatenate(docs)
    time = np.arange(len(flat)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    order = np.argsort(time, kind="stable")
    return flat[order], np.concatenate(([0], np.cumsum(np.bincount(time))))


def forward(model: Model, docs: list[np.ndarray], keep: bool = False):
    """Natural log-likelihoods of documents in falling length; with keep also what the backward pass needs."""
    symbols, at = _time_major(docs)
    b = model.emits[symbols]
    a, scale = (np.empty_like(b), np.empty(len(b)))
    d = at[1]
    logs = np.zeros(d)
    x = model.start * b[:d]
    for t in range(len(at) - 1):
        lo, hi = at[t], at[t + 1]
        if t:
            x = (x[: hi - lo] @ model.moves) * b[lo:hi]
        s = x.sum(1)
        x /= s[:, None]
        logs[: hi - lo] += np.log(s)
        if keep:
            a[lo:hi], scale[lo:hi] = x, s
    return (logs, symbols, at, b, a, scale) if keep else logs


class Counts:
    """Expected counts of one Baum-Welch pass."""

    def __init__(self, model: Model):
        self.model, k = model, len(model.start)
        self.start, self.moves, self.emits, self.log = np.zeros(k), np.zeros((k, k)), np.zeros(model.emits.shape), 0.0

    def add(self, docs: list[np.ndarray]) -> None:
        m = self.model
        logs, symbols, at, b, a, scale = forward(m, docs, True)
        self.log += logs.sum()
        g = np.ones_like(a)  # scaled backward values; 1 at each document's end
        moves = np.zeros_like(self.moves)
        for t in range(len(at) - 2, 0, -1):
            lo, hi = at[t], at[t + 1]
            x = b[lo:hi] * g[lo:hi] / scale[lo:hi, None]
            first = at[t - 1]
            g[first : first + hi - lo] = x @ m.moves.T
            moves += a[first : first + hi - lo].T @ x
        self.moves += moves * m.moves
        g *= a
        self.start += g[: at[1]].sum(0)
        for k in range(g.shape[1]):
            self.emits[:, k] += np.bincount(symbols, g[:, k], len(self.emits))


def reestimate(start: np.ndarray, moves: np.ndarray, emits: np.ndarray, unigram: np.ndarray, prior: float = 200.0) -> Model:
    """M step. Emissions are smoothed by `prior` tokens of the corpus's unigram, so no symbol is impossible."""
    k = len(start)
    e = emits + prior * unigram[:, None]
    return Model((start + 1) / (start.sum() + k), (moves + 1) / (moves.sum(1, keepdims=True) + k), e / e.sum(0))


def initial_model(texts: list[str], symbols: Symbols, unigram: np.ndarray, states: int, steps: int, seed: int = 7) -> Model:
    """EM on the sample from a random start. Documents drift to states by their words, as moves start sticky."""
    rng = np.random.default_rng(seed)
    docs = sorted((symbols.of(token_codes(t)) for t in texts), key=len, reverse=True)
    emits = unigram[:, None] * rng.gamma(2.0, 0.5, (len(unigram), states))
    moves = np.full((states, states), 0.1 / max(1, states - 1))
    np.fill_diagonal(moves, 0.9)
    model = Model(np.full(states, 1 / states), moves, emits / emits.sum(0))
    for _ in range(steps if docs else 0):
        c = Counts(model)
        for g in _groups(np.array([len(d) for d in docs]), 200_000):
            c.add([docs[i] for i in g])
        model = reestimate(c.start, c.moves, c.emits, unigram, 20.0)
    return model


def _symbol_docs(text: pa.Array, symbols: Symbols) -> tuple[list[np.ndarray], list[np.ndarray]]:
    tokens = token_arrays(text)
    if not tokens:
        return [], []
    flat = symbols.of(np.concatenate(tokens))
    return tokens, np.split(flat, np.cumsum([len(t) for t in tokens])[:-1])


#: Bytes of text in one slice of a training or scoring pass: documents of like length share their time steps, so larger slices need fewer.
PASS_SLICE = 8 << 20


def _count_tokens(part: pa.RecordBatch) -> pa.RecordBatch:
    c, n = np.unique(np.concatenate(token_arrays(part.column("text"))), return_counts=True)
    return pa.RecordBatch.from_arrays([pa.array(c), pa.array(n.astype(np.int64))], ["code", "n"])


@dataclass
class Language:
    """A trained model with what scoring needs; `counts` is a table (code, c), the rest is bounded."""

    model: Model
    symbols: Symbols
    class_tokens: np.ndarray
    class_kinds: np.ndarray
    counts: DataFrame
    tokens: int
    kinds: int
    log: list[float]


def _start_sample(text: DataFrame, sample: int, longest: int) -> list[str]:
    """`sample` distinct texts of `longest` characters at most, by least hash: the same in every run, and copies of one text count once.

    A cut on the hash, set by the number of distinct texts, comes before the ordering, so that tasks send about `sample` texts together and not each.
    """
    short = text.where(F.length("text") <= longest).select("text", F.xxhash64("text").alias("h"))
    kinds = short.agg(F.approx_count_distinct("h")).first()[0]
    if kinds > 4 * sample:
        short = short.where(F.col("h") < int(3 * sample / kinds * 2**64) - 2**63)
    return [r["text"] for r in short.groupBy("h").agg(F.min("text").alias("text")).orderBy("h").limit(sample).collect()]


def train(docs: DataFrame, text_col: str = "text", frequent: int = 32_768, states: int = 8, passes: int = 2, sample: int = 768, longest: int = 16_384, steps: int = 8) -> Language:
    """Learns from all rows of `docs`."""
    text = docs.select(F.col(text_col).alias("text"))
    counts = materialize(text.mapInArrow(over_slices(_count_tokens, PASS_SLICE), "code long, n long").groupBy("code").agg(F.sum("n").alias("c")), "tokens")
    whole = counts.agg(F.sum("c").alias("tokens"), F.count("*").alias("kinds")).first()
    top = counts.where(F.col("c") >= cutoff(counts, frequent)).toPandas().sort_values("code")
    symbols = Symbols(top["code"].to_numpy(np.int64), top["c"].to_numpy(np.int64))
    per_class = F.shiftrightunsigned("code", 56).cast("int")
    class_tokens, class_kinds = np.zeros(CLASSES, np.int64), np.zeros(CLASSES, np.int64)
    for r in counts.groupBy(per_class.alias("k")).agg(F.sum("c").alias("n"), F.count("*").alias("v")).collect():
        class_tokens[r["k"]], class_kinds[r["k"]] = r["n"], r["v"]
    own = class_of(symbols.codes)
    class_tokens -= np.bincount(own, symbols.counts, CLASSES).astype(np.int64)
    class_kinds -= np.bincount(own, minlength=CLASSES)
    unigram = np.concatenate((symbols.counts, class_tokens)) + 1.0
    unigram /= unigram.sum()
    model = initial_model(_start_sample(text, sample, longest), symbols, unigram, states, steps)
    logs = []
    for _ in range(passes):
        model, log = _full_pass(text, model, symbols, unigram)
        logs.append(log)
    return Language(model, symbols, class_tokens, class_kinds, counts, whole["tokens"] or 0, whole["kinds"] or 0, logs)


def _full_pass(text: DataFrame, model: Model, symbols: Symbols, unigram: np.ndarray) -> tuple[Model, float]:
    shared = text.sparkSession.sparkContext.broadcast((model, symbols))
    k = len(model.start)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m, s = shared.value
        c = Counts(m)
        for batch in batches:
            for part in slices(batch, PASS_SLICE):
                _, docs = _symbol_docs(part.column("text"), s)
                for g in _groups(np.array([len(d) for d in docs], np.int64), 150_000):
                    c.add([docs[i] for i in g])
        used = np.flatnonzero(c.emits.any(1))
        rest = [*c.moves, c.start, np.array([c.log, *[0.0] * (k - 1)])]
        values = np.vstack([c.emits[used], *[r[None] for r in rest]])
        at = np.concatenate((used, -1 - np.arange(len(rest)))).astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(at), *[pa.array(values[:, i].copy()) for i in range(k)]], ["symbol", *[f"x{i}" for i in range(k)]])

    parts = text.mapInArrow(run, "symbol long, " + ", ".join(f"x{i} double" for i in range(k)))
    total = parts.groupBy("symbol").agg(*[F.sum(f"x{i}").alias(f"x{i}") for i in range(k)]).toPandas()
    emits, rest = np.zeros(model.emits.shape), np.zeros((k + 2, k))
    at, values = total["symbol"].to_numpy(), total.drop(columns="symbol").to_numpy()
    emits[at[at >= 0]] = values[at >= 0]
    rest[-1 - at[at < 0]] = values[at < 0]
    shared.destroy()
    return reestimate(rest[k], rest[:k], emits, unigram), float(rest[k + 1][0])


def score(docs: DataFrame, language: Language, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id, n_tokens, n_known, base_score, score; one row per document. log10 throughout.

    base_score is the add-one unigram over all tokens; score the model's probability of the whole text, its end included.
    """
    lang = language
    shared = docs.sparkSession.sparkContext.broadcast((lang.model, lang.symbols))
    denominator = lang.tokens + lang.kinds + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, symbols = shared.value
        base = np.log10((symbols.counts + 1) / denominator)
        n = len(symbols.codes)

        def work(part: pa.RecordBatch) -> pa.RecordBatch:
            tokens, docs = _symbol_docs(part.column("text"), symbols)
            score = np.zeros(len(docs))
            for g in _groups(np.array([len(d) for d in docs], np.int64), 150_000):
                score[g] = forward(model, [docs[i] for i in g]) / math.log(10)
            often = [d[d < n] for d in docs]
            rare = [np.unique(t[d >= n], return_counts=True) for t, d in zip(tokens, docs, strict=True)]
            columns = {
                "id": part.column("id"),
                "n_tokens": pa.array([len(t) for t in tokens], pa.int64()),
                "n_frequent": pa.array([len(o) for o in often], pa.int64()),
                "base_frequent": pa.array([float(base[o].sum()) for o in often], pa.float64()),
                "rare": list_array([r for r, _ in rare], pa.int64()),
                "times": list_array([t.astype(np.int32) for _, t in rare], pa.int32()),
                "forward": pa.array(score),
            }
            return pa.RecordBatch.from_arrays(list(columns.values()), list(columns))

        yield from over_slices(work, PASS_SLICE)(batches)

    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = docs.schema[id_col].dataType.simpleString()
    scored = rows.mapInArrow(run, f"id {kind}, n_tokens long, n_frequent long, base_frequent double, rare array<long>, times array<int>, forward double")
    scored = materialize(scored.withColumn("row", F.monotonically_increasing_id()), "scored")
    rare = scored.select("row", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("row", F.col("x.rare").alias("code"), F.col("x.times").alias("times"))
    spread = F.array(*[F.lit(math.log10(int(t) + int(v) + 1)) for t, v in zip(lang.class_tokens, lang.class_kinds, strict=True)])
    c = F.coalesce("c", F.lit(0))
    found = rare.join(lang.counts, "code", "left")
    sums = found.groupBy("row").agg(
        F.sum(F.when(F.col("c").isNotNull(), F.col("times"))).alias("known"),
        F.sum(F.col("times") * (F.log10(c + 1) - math.log10(denominator))).alias("base_rare"),
        F.sum(F.col("times") * (F.log10(c + 1) - F.get(spread, F.shiftrightunsigned("code", 56).cast("int")))).alias("rare_score"),
    )
    out = scored.drop("rare", "times").join(sums, "row", "left")
    zero = F.lit(0)
    return out.select(
        F.col("id").alias(id_col),
        "n_tokens",
        (F.col("n_frequent") + F.coalesce("known", zero)).alias("n_known"),
        (F.col("base_frequent") + F.coalesce("base_rare", zero)).alias("base_score"),
        (F.col("forward") + F.coalesce("rare_score", zero)).alias("score"),
    )
