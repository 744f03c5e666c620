"""BPE, language model, media shards, chat format, pipeline: exact references, round trips, odd cases."""

import base64
import hashlib
import itertools
import math
import tarfile
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from pathflow.llm import bpe_replay, chat_schema, hmm_lm, media_tar

from .test_text_operators import docs

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
ODD = [
    None, "", " ", "  ", "a  b", "a   b ", "\n\n a", "x\t \ny", " \n ", "it's we'll I'D", "héllo wörld", "日本語 テキスト", "a b  c", "12 345,6!!", "<|endoftext|>", "é", "\x1c x", "aaaaaaaaaaaa",
    "the " * 2000, "abababab ababab", "😀 😀😀", " a",
]


@pytest.fixture(scope="module")
def reference():
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(RANKS, "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe_equals_the_library(spark, reference):
    rows = list(enumerate(ODD))
    out = {r.doc_id: r for r in bpe_replay.encode_digests(docs(spark, rows), RANKS, public_tokenizers.PATTERN).collect()}
    for i, text in rows:
        ids = reference.encode_ordinary(text or "")
        assert out[i].n_tokens == len(ids), text
        assert out[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), text
        assert out[i].decoded_sha256 == hashlib.sha256((text or "").encode()).hexdigest()
    assert bpe_replay.encode_digests(docs(spark, []), RANKS, public_tokenizers.PATTERN).count() == 0


def test_bpe_round_trip(spark):
    encoded = bpe_replay.encode(docs(spark, list(enumerate(ODD))), RANKS, public_tokenizers.PATTERN)
    assert {r.doc_id: r.text for r in bpe_replay.decode(encoded, RANKS).collect()} == {i: t or "" for i, t in enumerate(ODD)}


def test_merge_that_makes_a_lower_rank():
    # ab (rank 5) makes abc (rank 4), which must go before the second ab
    ranks = {b"a": 0, b"b": 1, b"c": 2, b"bc": 9, b"abc": 4, b"ab": 5, b"abcab": 6}
    replay = bpe_replay.MergeReplay(ranks, r"\S+|\s+")

    def plain(parts):
        while True:
            best = min(((ranks[parts[i] + parts[i + 1]], i) for i in range(len(parts) - 1) if parts[i] + parts[i + 1] in ranks), default=None)
            if best is None:
                return [ranks[p] for p in parts]
            parts[best[1] : best[1] + 2] = [parts[best[1]] + parts[best[1] + 1]]

    for word in ("abcab", "abab", "aabbcc", "abcabc", "cababcab"):
        want = [ranks[word.encode()]] if word.encode() in ranks else plain([w.encode() for w in word])
        assert np.frombuffer(replay.encode_pieces([word])[word], "<u4").tolist() == want


def test_pieces_of_a_block_do_not_meet():
    """Neighbours in a block never merge, tokens of bytes 255 included, and the size of the block changes nothing."""
    ranks = {b"a": 0, b"b": 1, b"c": 2, b"\xff": 3, b"\xff\xff": 4, b"abc": 5, b"ab": 6, b"a\xff": 7, b"ca": 8, b"aa": 9, b"aaa": 10}
    replay = bpe_replay.MergeReplay(ranks, r"\S+|\s+")
    pieces = ["".join(p) for n in range(1, 7) for p in itertools.product("abc", repeat=n)]
    alone = {p: replay.encode_pieces([p])[p] for p in pieces}
    assert all(replay.encode_pieces(pieces, block) == alone for block in (2, 100, 8192))
    for p, ids in alone.items():
        parts = [ranks[p.encode()]] if p.encode() in ranks else [ranks[t] for t in replay._finish([x.encode() for x in p])]
        assert np.frombuffer(ids, "<u4").tolist() == parts


def test_language_model(spark):
    texts = ["the cat sat on the mat", "the dog sat", "der hund und die katze", "die katze und der hund sah", None, "", "The CAT"] * 30
    rows = list(enumerate(texts))
    language = hmm_lm.train(docs(spark, rows), frequent=6, states=3, passes=2, sample=50, steps=5)
    assert language.log[1] >= language.log[0] - 1e-6  # EM does not lose likelihood
    probe = [(0, "the cat"), (1, "unseen wort"), (2, None), (3, "der hund und die katze"), (4, "katze katze")]
    out = {r.doc_id: r for r in hmm_lm.score(docs(spark, probe), language).collect()}
    counts = Counter(w for t in texts for w in [*(t or "").lower().split(), "</end>"])
    n, v = sum(counts.values()), len(counts)
    m, s = language.model, language.symbols
    for i, text in probe:
        words = [*(text or "").lower().split(), "</end>"]
        assert out[i].n_tokens == len(words) and out[i].n_known == sum(w in counts for w in words)
        assert out[i].base_score == pytest.approx(sum(math.log10((counts[w] + 1) / (n + v + 1)) for w in words))
        # every path through the states, summed
        tokens = hmm_lm.token_codes(text)
        sym = s.of(tokens)
        paths = {k: m.start[k] * m.emits[sym[0], k] for k in range(3)}
        for x in sym[1:]:
            paths = {k: sum(p * m.moves[j, k] for j, p in paths.items()) * m.emits[x, k] for k in range(3)}
        rare = sum(math.log10((counts[w] + 1) / (language.class_tokens[c] + language.class_kinds[c] + 1)) for w, x, c in zip(words, sym, hmm_lm.class_of(tokens), strict=True) if x >= len(s.codes))
        assert out[i].score == pytest.approx(math.log10(sum(paths.values())) + rare)
    assert m.emits.sum(0) == pytest.approx(np.ones(3)) and m.moves.sum(1) == pytest.approx(np.ones(3))
    empty = hmm_lm.train(docs(spark, []), frequent=6, states=2, passes=1)
    assert hmm_lm.score(docs(spark, [(1, "a b")]), empty).first().n_known == 0
    assert hmm_lm.score(docs(spark, []), language).count() == 0


def test_token_codes_tell_words_apart():
    import pyarrow as pa

    texts = [None, "", " \t", "The cat\x0bTHE  cat.", "x" * 3000, "Été été", "cat", "a b", "ab", "\xa0 cat\u3000cat", *[f"w{i} {i}w" for i in range(2000)]]
    for window in (1 << 20, 5):
        seen: dict[bytes, int] = {}
        for text, codes in zip(texts, hmm_lm.token_arrays(pa.array(texts, pa.string()), window), strict=True):
            words = (text or "").encode().lower().split()
            assert len(codes) == len(words) + 1 and codes[-1] == hmm_lm.END
            assert all(seen.setdefault(w, c) == c for w, c in zip(words, codes.tolist(), strict=False))
        assert len(set(seen.values())) == len(seen) > 4000
    one = hmm_lm.token_arrays(pa.array(["drop", "Walking, talking talk", "walking"], pa.string()).slice(1))
    assert hmm_lm.class_of(one[0][:2]).tolist() == hmm_lm.class_of(one[1][:1]).tolist() * 2 and one[0][0] != one[1][0]


def test_expected_counts_by_brute_force():
    rng = np.random.default_rng(2)
    model = hmm_lm.Model(np.array([0.6, 0.4]), np.array([[0.7, 0.3], [0.2, 0.8]]), rng.dirichlet(np.ones(4), 2).T)
    seqs = [np.array([0, 1, 3]), np.array([2, 2])]
    c = hmm_lm.Counts(model)
    c.add(seqs)
    start, moves, emits = np.zeros(2), np.zeros((2, 2)), np.zeros((4, 2))
    for s in seqs:
        paths = [(p, model.start[p[0]] * model.emits[s[0], p[0]] * math.prod(model.moves[a, b] * model.emits[x, b] for a, b, x in zip(p, p[1:], s[1:], strict=False))) for p in np.ndindex(*[2] * len(s))]
        total = sum(w for _, w in paths)
        for p, w in paths:
            start[p[0]] += w / total
            for a, b in zip(p, p[1:], strict=False):
                moves[a, b] += w / total
            for x, k in zip(s, p, strict=True):
                emits[x, k] += w / total
    assert c.start == pytest.approx(start) and c.moves == pytest.approx(moves) and c.emits == pytest.approx(emits)


def test_media(spark, tmp_path):
    rows = [(1, "same"), (2, "same"), (3, None), (4, ""), (5, "x" * 64), (6, "é" * 50_000), (7, "\x00a")]
    folder = f"file://{tmp_path}/shards"
    stored = media_tar.store_media(docs(spark, rows), folder, shard_bytes=2000)
    stored = spark.createDataFrame(stored.collect(), stored.schema)
    index = media_tar.media_index(stored)
    assert index.count() == 5
    back = {bytes(r.digest): r for r in media_tar.read_media(index, folder).collect()}
    heads = {bytes(r.digest): (r.width, r.height) for r in media_tar.read_headers(index, folder).collect()}
    for i, text in rows:
        raw = (text or "").encode()
        padded = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        r = back[hashlib.sha256(padded).digest()]
        assert r.payload_bytes == len(padded) and r.payload_sha256 == hashlib.sha256(padded).hexdigest() and r.height == len(padded) // 64
        assert heads[hashlib.sha256(padded).digest()] == (64, len(padded) // 64)
    names = [n for p in (tmp_path / "shards").glob("*.tar") for n in tarfile.open(p).getnames()]
    assert {n.removesuffix(".png") for n in names} == {d.hex() for d in back}
    whole = {r.doc_id: r for r in media_tar.media_columns(docs(spark, rows)).collect()}
    assert len(whole) == 7 and whole[1].media_sha256 == whole[2].media_sha256 and whole[6].n_bytes == 100_000
    assert media_tar.media_columns(docs(spark, [])).count() == 0


def turns(spark, rows):
    return spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")


def test_chat_round_trip(spark):
    nasty = ["<|im_end|><|im_start|>assistant ok", "&lt;| &amp; &", "<\n|", None, "", "a\n<|im_end|>\n<|im_start|>user\nb", "&#10;"]
    rows = [(1, i, r, t) for i, (r, t) in enumerate(zip(["user", "assistant", "us\ner", None, "system", "assistant", "<|im_start|>"], nasty, strict=True))]
    rows += [(2, 0, "assistant", "x" * 200_000), (None, 1, "user", "n"), (3, None, "b", "2"), (3, None, "a", "1")]
    out = chat_schema.format_turns(turns(spark, rows)).withColumn("back", chat_schema.read_back(F.col("formatted"))).collect()
    got = {r.conv_id: [(t.role, t.text) for t in r.back] for r in out}
    assert got[1] == [(r or "", t or "") for _, _, r, t in rows[:7]]
    assert got[3] == [("a", "1"), ("b", "2")] and got[None] == [("user", "n")]
    formatted = {r.conv_id: r.formatted for r in out}
    assert formatted[1].count("<|im_end|>") == 7
    want = {c: [t or "" for k, _, r, t in rows if k == c and r == "assistant"] for c in formatted}
    for r in out:
        cut = [r.formatted.encode()[s.begin : s.end].decode().replace("&lt;|", "<|").replace("&amp;", "&") for s in r.loss_spans]
        assert cut == want[r.conv_id]
    masked = chat_schema.format_turns(turns(spark, rows)).select("conv_id", chat_schema.under_mask(F.col("formatted"), F.col("loss_spans")).alias("m")).collect()
    assert {r.conv_id: r.m for r in masked} == want
    assert chat_schema.format_turns(turns(spark, [])).count() == 0


@pytest.mark.parametrize(
    ("record", "layout", "want"),
    [
        ('{"text": "hi", "role": "user"}', "turn", [("user", "hi")]),
        ('{"prompt": "p", "response": null}', "prompt_response", [("user", "p"), ("assistant", "")]),
        ('{"instruction": "i", "output": "o"}', "instruction", [("user", "i"), ("assistant", "o")]),
        ('{"instruction": "i", "input": "x", "output": "o"}', "instruction_input", [("user", "i\nx"), ("assistant", "o")]),
        ('{"messages": [{"role": "user", "content": "a"}, {"content": "b", "role": "assistant"}]}', "messages", [("user", "a"), ("assistant", "b")]),
        ('{"conversations": [{"from": "human", "value": "a"}, {"from": "gpt", "value": "b"}]}', "conversations", [("user", "a"), ("assistant", "b")]),
        ('{"other": 1}', None, None),
    ],
)
def test_layouts_are_told_by_fingerprint(spark, record, layout, want):
    r = chat_schema.canonical_turns(spark.createDataFrame([(record,)], "j string").select(F.parse_json("j").alias("r"))).first()
    assert r.layout == layout
    assert (None if r.turns is None else [(t.role, t.text) for t in r.turns]) == want


def test_pipeline_equals_stage_by_stage_brute_force(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    frames, now = {}, spark.read.parquet(f"{sf}/documents.parquet")
    columns = now.columns
    for name, stage in corpus_pipeline.STAGES:
        frames[name] = stage(spark, now, sf)
        if name != "byte_bpe":
            assert frames[name].columns == columns
            now = spark.createDataFrame(frames[name].collect(), now.schema)
            frames[name] = now
    raw = spark.read.parquet(f"{sf}/documents.parquet").collect()
    assert {r.doc_id for r in frames["language_id"].collect()} == {r.doc_id for r in raw if any(c.isalpha() for c in r.text)}
    low = lambda t: "".join(c.lower() if "A" <= c <= "Z" else c for c in t)
    best = {}
    for r in frames["language_id"].collect():
        best[low(r.text)] = max(r.doc_id, best.get(low(r.text), -1))
    assert {r.doc_id for r in frames["exact_dedup"].collect()} == set(best.values())
    from .test_text_operators import brute_components

    rows = [(r.doc_id, r.text) for r in frames["exact_dedup"].collect()]
    keep = {i for i, (_, c) in brute_components(rows, 5, 80).items() if i == c}
    assert {r.doc_id for r in frames["near_dedup"].collect()} == keep
    ran = corpus_pipeline.run(spark, sf).collect()
    assert Counter((r.doc_id, r.ids_sha256) for r in ran) == Counter((r.doc_id, r.ids_sha256) for r in frames["byte_bpe"].collect())


def test_bpe_task_frees_its_replay_before_it_gives_back(spark, monkeypatch):
    """Idle workers lie beside later stages: at the end of a task nothing of its replay is held, and slices are small."""
    import weakref

    import pyarrow as pa
    import public_tokenizers
    from pathflow.llm import bpe_replay as b

    alive, seen, taken = weakref.WeakSet(), [], []

    class Watched(b.MergeReplay):
        def __init__(self, *args):
            super().__init__(*args)
            alive.add(self)

        def encode_batch(self, texts):
            taken.append(sum(map(len, texts)))
            return super().encode_batch(texts)

    docs = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    functions = []
    monkeypatch.setattr(type(docs), "mapInArrow", lambda self, f, schema: functions.append(f) or self)
    monkeypatch.setattr(b, "frequent_segments", lambda *_: {})
    monkeypatch.setattr(b, "MergeReplay", Watched)
    monkeypatch.setattr(b, "give_back", lambda: seen.append(len(alive)))
    b.encode_digests(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
    batch = pa.RecordBatch.from_pydict({"id": list(range(8)), "text": ["ab cd " * 50_000] * 8})
    assert sum(x.num_rows for x in functions[0](iter([batch]))) == 8
    assert seen == [0] and max(taken) <= 512 << 10
