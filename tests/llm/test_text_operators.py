"""Exact dedup, near dedup, mixing, sharding, language ID, quality: small fixtures against brute force, and the odd cases."""

import random
import zlib
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from pathflow.llm import exact_dedup, kd_shards, langid_rank, mix_hist, quality_pu, superminhash
from pathflow.llm.components import connected_components
from pathflow.llm.superminhash import band_keys, signature

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, id string, size long, comp string, h long, kept string, row string, score string, copies string, shard int"


def docs(spark, rows):
    """rows of (doc_id, text[, lang, source]); the extra columns clash with names that operators use inside."""
    full = [(r[0], r[1], r[2] if len(r) > 2 else "en", r[3] if len(r) > 3 else "s", 0, "x", 1, "c", 2, "k", "r", "s", "n", 5) for r in rows]
    return spark.createDataFrame(full, SCHEMA)


def vary(rng, words, share):
    return [w if rng.random() > share else f"n{rng.randrange(10**6)}" for w in words]


@pytest.fixture(scope="module")
def mixed():
    rng = random.Random(3)
    base = [[f"w{rng.randrange(400)}" for _ in range(n)] for n in (3, 40, 60, 90, 120)]
    rows, i = [], 0
    for words in base:
        for share in (0, 0, 0, 0.01, 0.01, 0.02, 0.03, 0.05, 0.1):
            rows.append((i, " ".join(vary(rng, words, share)) if share else " ".join(words)))
            i += 1
    rows += [(i, None), (i + 1, ""), (i + 2, " \n\t"), (i + 3, "One two"), (i + 4, "one  TWO"), (i + 5, "É b"), (i + 6, "é b"), (i + 7, "w1 " * 30_000)]
    return rows


def words_of(text):
    return [] if text is None else text.encode().lower().split()


def shingles(text, k):
    w = words_of(text)
    return {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def brute_components(rows, k, percent):
    root = {i: i for i, _ in rows}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    sets = {i: shingles(t, k) for i, t in rows}
    for a, b in combinations(sets, 2):
        both = len(sets[a] & sets[b])
        if sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i, _ in rows}


@pytest.mark.parametrize(("k", "percent"), [(4, 80), (5, 80)])
def test_near_duplicates_equal_brute_force(spark, mixed, k, percent):
    out = superminhash.near_duplicate_components(docs(spark, mixed), shingle=k, percent=percent).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in out} == brute_components(mixed, k, percent)
    assert all(r.kept == (r.component_id == r.doc_id) for r in out)


def test_near_duplicates_of_nothing_and_null_ids(spark):
    assert superminhash.near_duplicate_components(docs(spark, [])).count() == 0
    out = superminhash.near_duplicate_components(docs(spark, [(None, "a b c d e f"), (4, "a b c d e f"), (4, "a b c d e f"), (9, "a b c d e f")])).collect()
    assert sorted((r.doc_id or -1, r.component_id or -1, r.kept) for r in out) == [(-1, -1, False), (4, 4, True), (4, 4, True), (9, 4, False)]


def test_one_bucket_of_unlike_documents_loses_no_link(spark):
    # a shared passage makes them meet; only some link
    rng = random.Random(9)
    common = [f"c{i}" for i in range(60)]
    rows = [(i, " ".join(common + [f"u{i % 20}_{j}" for j in range(14 + i % 3)])) for i in range(60)]
    rng.shuffle(rows)
    out = superminhash.near_duplicate_components(docs(spark, rows), shingle=4, percent=80).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in out} == brute_components(rows, 4, 80)


def test_superminhash_estimates_jaccard():
    import numpy as np

    rng = np.random.default_rng(1)
    errors = []
    for _ in range(40):
        x = rng.integers(0, 2**63, 300).astype(np.uint64)
        a, b = signature(x[:250]), signature(x[50:])
        errors.append((a == b).mean() - 200 / 300)
    assert abs(np.mean(errors)) < 0.03 and np.std(errors) < 0.05
    one = signature(x[:1])
    assert len(np.unique(one >> np.uint64(32))) == 128  # one element: one slot a level
    assert (band_keys(a, 32) == band_keys(a.copy(), 32)).all()


def test_components(spark):
    edges = [(1, 2), (2, 3), (9, 8), (8, 7), (7, 3), (20, 21), (5, 5), *((i, i + 1) for i in range(100, 140))]
    labels = {r.node: r.root for r in connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert labels == {2: 1, 3: 1, 7: 1, 8: 1, 9: 1, 21: 20, **{i: 100 for i in range(101, 141)}}
    assert connected_components(spark.createDataFrame([(1, 1)], "u long, v long")) is None


def test_exact_dedup(spark, mixed):
    rows = mixed + [(500, "One Two"), (501, "oNE two"), (None, "one two"), (502, "solo"), (502, "solo")]
    out = exact_dedup.mark_exact(docs(spark, rows), keep="max", columns=["doc_id"]).collect()
    groups = {}
    for i, t in rows:
        groups.setdefault("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""), []).append(i)
    want = sorted((i is None, i or 0, max(x for x in g if x is not None), len(g)) for g in groups.values() for i in g)
    assert sorted((r.doc_id is None, r.doc_id or 0, r.keep_id, r.group_size) for r in out) == want
    kept = exact_dedup.drop_exact(docs(spark, rows), keep="max")
    assert sorted(r.doc_id for r in kept.collect()) == sorted(max(x for x in g if x is not None) for g in groups.values())
    assert kept.columns == docs(spark, []).columns
    assert exact_dedup.mark_exact(docs(spark, [])).count() == 0


def test_mix(spark):
    rng = random.Random(1)
    rows = [(i, " ".join(["w"] * rng.randrange(0, 60)), "en", rng.choice(["a", "a", "a", "a", "b", "Z", None, "é"])) for i in range(600)] + [(1000, None, "en", "a")]
    out = mix_hist.mix(docs(spark, rows)).collect()
    assert len(out) == len(rows)
    sizes = {}
    for r in out:
        sizes[r.source] = sizes.get(r.source, 0) + r.size
        assert r.taken <= 2 * r.size and r.taken == r.copies * r.size
    order = sorted((s for s in sizes if s is not None)) + [None]
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    budget, capped = 1.5 * sum(sizes.values()), set()
    while True:
        free = [s for s in order if s not in capped]
        left = budget - sum(2 * sizes[s] for s in capped)
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        more = {s for s in free if share[s] > 2 * sizes[s]}
        if not more:
            break
        capped |= more
    for s in order:
        target = share.get(s, 2 * sizes[s])
        got = [r for r in out if r.source == s]
        assert got[0].target == pytest.approx(target) and abs(sum(r.taken for r in got) - target) <= 60
    again = {(r.doc_id, r.taken) for r in mix_hist.mix(docs(spark, rows)).collect()}
    assert again == {(r.doc_id, r.taken) for r in out}
    more = {r.doc_id: r.taken for r in mix_hist.mix(docs(spark, rows), percent=160).collect()}
    if not capped:
        assert all(more[r.doc_id] >= r.taken for r in out)
    assert mix_hist.mix(docs(spark, [])).count() == 0


def test_kd_shards(spark):
    rng = random.Random(2)
    rows = spark.createDataFrame([(i, rng.randrange(1, 200), float(rng.choice([1, 1, 1, 2, 9])), rng.random(), None if i % 7 else 1.0) for i in range(3000)], "doc_id long, size long, a double, b double, c double")
    tree, placed = kd_shards.kd_shards(rows, ["a", "b", "c"], "size", F.xxhash64("doc_id"), 24)
    sums = [r[0] for r in placed.groupBy("shard").agg(F.sum("size")).select("sum(size)").collect()]
    assert len(sums) == 24 and max(sums) - min(sums) <= 5 * 200 and tree.leaves == 24
    slots = kd_shards.number_slots(placed, "shard", ["doc_id"], 16).groupBy("shard").agg(F.sort_array(F.collect_list("slot")).alias("s")).collect()
    assert all(r.s == list(range(len(r.s))) for r in slots)
    _, none = kd_shards.kd_shards(rows.limit(0), ["a"], "size", F.xxhash64("doc_id"), 24)
    assert none.count() == 0 and kd_shards.number_slots(none, "shard", ["doc_id"]).count() == 0
    same = rows.withColumn("a", F.lit(1.0)).withColumn("doc_id", F.lit(1).cast("long"))
    _, tied = kd_shards.kd_shards(same, ["a"], "size", F.xxhash64("doc_id"), 4)
    assert tied.count() == 3000  # one key: cannot be told apart, nothing is lost


def test_language_id(spark):
    texts = {"en": "the and of thing ing with that", "de": "der und ung schein über nicht keit", "fr": "le que été eau ment dans"}
    rng = random.Random(4)
    rows = [(i, " ".join(rng.choice(texts[lang].split()) for _ in range(20)), lang) for i, lang in enumerate(list(texts) * 30)]
    odd = [(900, None, "en"), (901, "", "en"), (902, "123 !?", "en"), (903, "the " * 50_000, None), (904, "THE AND OF", "xx")]
    train = docs(spark, rows + odd[:4])
    profiles = langid_rank.language_profiles(train)
    assert set(profiles) == set(texts)
    out = {r.doc_id: r for r in langid_rank.identify(docs(spark, rows + odd), profiles).collect()}
    assert all(out[i].lang_pred == lang and 0 <= out[i].score <= 1 for i, _, lang in rows)
    assert [out[i].lang_pred for i in (900, 901, 902)] == ["und"] * 3 and out[903].lang_pred == out[904].lang_pred == "en"
    assert langid_rank.identify(docs(spark, []), profiles).count() == 0
    assert [r.lang_pred for r in langid_rank.identify(docs(spark, rows[:2]), langid_rank.language_profiles(docs(spark, []))).collect()] == ["und", "und"]


def test_out_of_place_distance_by_hand():
    import numpy as np

    r = langid_rank.RankOrder({"a": np.array([1, 2, 3]), "b": np.array([3, 9, 1])}, 3)
    own = np.array([1, 2, 7])
    ranks = r.ranks[[0, 1, len(r.grams)]]
    assert ranks.tolist() == [[0, 2], [1, -1], [-1, -1]]
    assert langid_rank.ranked(np.unique([5, 5, 4, 4, 8], return_counts=True), 2).tolist() == [4, 5] and len(own) == 3


def test_quality(spark):
    rng = random.Random(8)
    good = lambda: " ".join(rng.choice("the and of to in that whose river runs".split()) + str(rng.randrange(9)) for _ in range(60)) + "."
    bad = lambda: " ".join([rng.choice(["buy", "NOW!!!", "$$$"])] * 60)
    rows = [(i, good() if i % 5 else bad()) for i in range(900)]
    labels = spark.createDataFrame([(i, 1 if i % 5 else 0) for i in range(0, 600, 2)] + [(None, 1), (5000, None)], "doc_id long, quality int")
    table = quality_pu.feature_table(docs(spark, rows))
    net, prior = quality_pu.train(table, labels)
    assert 0.6 < prior < 0.95
    out = {r.doc_id: r for r in quality_pu.score(table, net).collect()}
    right = sum(out[i].predicted == (1 if i % 5 else 0) for i in range(600, 900))
    assert right >= 290 and all(0 <= r.score <= 1 for r in out.values())
    odd = quality_pu.score(quality_pu.feature_table(docs(spark, [(1, None), (2, ""), (3, "x" * 400_000), (4, "\n")])), net).collect()
    assert len(odd) == 4 and all(0 <= r.score <= 1 for r in odd)
    none, half = quality_pu.train(table, labels.limit(0))
    assert half == 0.5 and {r.score for r in quality_pu.score(table.limit(3), none).collect()} == {0.5}
    assert quality_pu.score(quality_pu.feature_table(docs(spark, [])), net).count() == 0


def test_risk_never_uses_negatives_and_bounds_the_prior():
    import numpy as np

    rng = np.random.default_rng(0)
    p, n = rng.normal(2, 1, 4000), rng.normal(-2, 1, 1000)
    u = np.concatenate((rng.normal(2, 1, 3000), n))
    assert 0.7 < quality_pu.best_bin_prior(p, u) < 0.8


def test_id_crc_matches_zlib(spark):
    from pathflow.llm.common import id_crc

    rows = spark.createDataFrame([(7,), (123456789,), (None,)], "doc_id long").select("doc_id", id_crc(F.col("doc_id")).alias("c")).collect()
    assert [r.c for r in rows] == [zlib.crc32(str(r.doc_id).encode()) if r.doc_id is not None else 0 for r in rows]
