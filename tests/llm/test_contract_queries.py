"""The registered queries at the smallest scale against SQL or brute force: rules, column types and whole results."""

import base64
import hashlib
import math
import zlib
from collections import Counter

import duckdb
import numpy as np
import public_tokenizers
import pytest

from pathflow.llm import langid_rank, queries
from tests.test_queries import TABLES, rows

from .test_text_operators import brute_components

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def texts(spark):
    return {r.doc_id: r for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


def answer(spark, name):
    df = queries.QUERIES[name](spark, SF)
    return df, {r.doc_id: r for r in df.collect()}


def crc(i):
    return zlib.crc32(str(i).encode())


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_queries_with_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    got = con.execute(queries.ORACLES[name])
    names = [d[0] for d in got.description]
    df = queries.QUERIES[name](spark, SF)
    assert sorted(df.columns) == sorted(names)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(names, got.fetchall())


def test_op1(spark, texts):
    df, out = answer(spark, "op1_kd_sharding")
    assert dict(df.dtypes) == {"doc_id": "bigint", "size": "bigint", "text_crc32": "bigint", "law": "string", "shard": "int", "slot": "bigint", "grown_shard": "int"}
    sizes, slots = Counter(), {}
    for i, r in texts.items():
        raw = (r.text or "").encode()
        assert (out[i].size, out[i].text_crc32, out[i].law) == (len(raw) + 8, zlib.crc32(raw), "bytes")
        sizes[out[i].shard] += out[i].size
        slots.setdefault(out[i].shard, []).append(out[i].slot)
    assert set(sizes) <= set(range(24)) and all(sorted(s) == list(range(len(s))) for s in slots.values())
    # a cut misses its weight by half a row at most, on each of the five levels
    assert max(sizes.values()) - sum(sizes.values()) / 24 <= 2.5 * max(r.size for r in out.values())


def test_op2(spark, texts):
    _, out = answer(spark, "op2_pu_quality")
    assert set(out) == set(texts)
    assert all(r.held_out == (crc(i) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for i, r in out.items())


def test_op4(spark, texts):
    _, out = answer(spark, "op4_language_id")
    assert all(r.held_out == (crc(i) % 3 == 1) for i, r in out.items())
    assert all((r.lang_pred == "und") == (not any(c.isalpha() for c in texts[i].text or "")) for i, r in out.items())
    known = [i for i, r in out.items() if r.held_out and texts[i].lang and r.lang_pred != "und"]
    assert sum(out[i].lang_pred == texts[i].lang for i in known) >= 0.95 * len(known)


def test_out_of_place_distance_by_brute_force(texts):
    def grams(text):
        words = "".join(c if c.isalpha() else " " for c in text.lower()).split()
        run = " " + " ".join(words) + " "
        return Counter(run[i : i + n] for n in (1, 2, 3) for i in range(len(run) - n + 1) if run[i : i + n] != " ") if words else Counter()

    def code(gram):
        out = 0
        for c in gram:
            out = out << 21 | ord(c)
        return out

    def order(counts):
        return [code(x) for x, _ in sorted(counts.items(), key=lambda kv: (-kv[1], code(kv[0])))][:400]

    learned: dict[str, Counter] = {}
    for r in texts.values():
        learned.setdefault(r.lang, Counter()).update(grams(r.text or ""))
    profiles = {lang: order(c) for lang, c in learned.items() if lang}
    ranker = langid_rank.RankOrder({k: np.array(v, np.int64) for k, v in profiles.items()})
    for r in list(texts.values())[:60]:
        own = order(grams(r.text or ""))
        far = {lang: sum(min(abs(p.index(x) - i), 400) if x in p else 400 for i, x in enumerate(own)) for lang, p in profiles.items()}
        best = min(sorted(far), key=far.get) if own else "und"
        lang, score, _ = ranker.predict(r.text)
        assert lang == best and (not own or score == pytest.approx(1 - far[best] / (400 * len(own))))


def test_op5(spark, texts):
    _, out = answer(spark, "op5_superminhash")
    want = brute_components([(i, r.text) for i, r in texts.items()], 4, 80)
    assert {i: (r.n_shingles, r.component_id) for i, r in out.items()} == want and all(r.kept == (i == r.component_id) for i, r in out.items())


def test_op7(spark, texts):
    _, out = answer(spark, "op7_media_tar")
    seen = {}
    for i, r in texts.items():
        raw = (r.text or "").encode()
        padded = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        assert (out[i].n_bytes, out[i].payload_bytes, out[i].payload_sha256, out[i].tail_crc32) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-64:]))
        assert (out[i].width, out[i].height) == (64, len(padded) // 64)
        assert seen.setdefault(padded, (out[i].media_sha256, out[i].feature)) == (out[i].media_sha256, out[i].feature)


def test_op8(spark, texts):
    _, out = answer(spark, "op8_hmm_scores")
    tokens = {i: [*(r.text or "").encode().lower().split(), None] for i, r in texts.items()}
    counts = Counter(t for i, ts in tokens.items() if crc(i) % 7 != 2 for t in ts)
    n, v = sum(counts.values()), len(counts)
    for i, ts in tokens.items():
        r = out[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (crc(i) % 7 == 2, len(ts), sum(t in counts for t in ts), n)
        assert r.base_score == pytest.approx(sum(math.log10((counts[t] + 1) / (n + v + 1)) for t in ts)) and r.score < 0


def test_op9(spark, texts):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    _, out = answer(spark, "op9_bpe")
    for i, r in texts.items():
        found = np.array(library.encode_ordinary(r.text or ""), "<u4")
        assert (out[i].n_tokens, out[i].ids_sha256) == (len(found), hashlib.sha256(found.tobytes()).hexdigest())
        assert out[i].decoded_sha256 == hashlib.sha256((r.text or "").encode()).hexdigest()


def test_long_distinct_text_near_duplicates(spark):
    from pathflow.llm import superminhash

    from .test_text_operators import docs

    words = [f"w{i}" for i in range(60_000)]
    near = words[:100] + ["x"] + words[101:]
    given = [(1, " ".join(words)), (2, " ".join(near)), (3, " ".join(reversed(words)))]
    out = superminhash.near_duplicate_components(docs(spark, given), shingle=5, percent=80).collect()
    assert {r.doc_id: r.component_id for r in out} == {1: 1, 2: 1, 3: 3}
