"""Further cases: no language left out, long insertions, range reads, estimates and scores by plain arithmetic."""

from __future__ import annotations

import math
import random
from collections import Counter

import numpy as np
import pytest

from standq.llm import common, decontaminate, embed_dedup, langid, license_scan, pii, quality_mil, simhash, sstable
from standq.scratch import scratch


def test_every_language_is_learned(spark):
    """1,100 languages of two documents each, every one with letters of its own."""
    rng = random.Random(4)
    words = {n: ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(7)) for _ in range(12)] for n in range(1100)}
    rows = [(2 * n + k, " ".join(rng.choices(words[n], k=30)), f"l{n:04d}") for n in words for k in range(2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(4)
    learnable = {r.lang for r in docs.filter(langid.fold("doc_id", 4) != 2).select("lang").distinct().collect()}
    model = langid.train(docs)
    assert len(learnable) > 1000 and set(model.languages) == learnable


def test_centroid_scores_by_plain_arithmetic(spark):
    """Predictions are the nearest centroid by cosine of log-counts times inverse frequencies over all learnable texts."""
    rng = random.Random(2)
    stems = {"a": "the of and to in is that".split(), "b": "der die und das ist nicht ein".split()}
    rows = [(i, " ".join(rng.choices(stems[k], k=25)), k) for i, k in enumerate("ab" * 30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").repartition(3)
    model = langid.train(docs)
    held = {r.doc_id for r in docs.filter(langid.fold("doc_id", 4) == 2).collect()}
    learned = [langid.grams(t) for i, t, _ in rows if i not in held]
    for j in range(0, langid.DIM, 7):
        seen = sum(1 for c in learned if c[j])
        assert math.isclose(model.idf[j], math.log((1 + len(learned)) / (1 + seen)) + 0.2, rel_tol=1e-12)
    got = {r.doc_id: r for r in langid.identify(docs, model).collect()}
    for i, t, _ in rows[:12]:
        v = [math.log1p(c) * w for c, w in zip(langid.grams(t).tolist(), model.idf.tolist(), strict=True)]
        size = math.sqrt(sum(x * x for x in v))
        near = [(sum(x * y for x, y in zip(v, c, strict=True)) / size, -k) for k, c in enumerate(model.centers.tolist())]
        best, k = max(near)
        assert abs(got[i].similarity - best) < 1e-4 and got[i].nearest_lang == model.languages[model.owners[-k]]


def test_attention_scores_by_plain_arithmetic():
    rng = np.random.default_rng(5)
    model = quality_mil.GatedAttention()
    bag = rng.normal(size=(4, quality_mil.N_FEATURES)).astype(np.float32)
    p = {k: v.tolist() for k, v in model.p.items()}
    dot = lambda x, m: [sum(a * r[j] for a, r in zip(x, m, strict=True)) for j in range(len(m[0]))]
    h = [[math.tanh(a + b) for a, b in zip(dot(np.clip(x, -6, 6).tolist(), p["E"]), p["e"], strict=True)] for x in bag.astype(float)]
    s = [sum(w * math.tanh(a) / (1 + math.exp(-b)) for w, a, b in zip(p["w"], dot(x, p["V"]), dot(x, p["U"]), strict=True)) for x in h]
    a = [math.exp(x) / sum(map(math.exp, s)) for x in s]
    z = sum(c * sum(w * x[j] for w, x in zip(a, h, strict=True)) for j, c in enumerate(p["c"])) + p["d"][0]
    assert abs(model.score([bag])[0] - 1 / (1 + math.exp(-z))) < 1e-9


def test_training_is_bounded_when_identifiers_repeat(spark):
    docs = spark.createDataFrame([(i % 5, f"text {i} " * 50) for i in range(400)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(5)], "doc_id long, quality int")
    model = quality_mil.train(docs, labels, most=7)
    assert model.constant is not None or model.score([quality_mil.features("text")]).shape == (1,)


def test_license_torn_apart(spark):
    """An insertion of any length into a long notice does not hide it; short notices must stand together."""
    own = license_scan.TEMPLATES["ISC"].split()
    filler = " ".join(f"w{i}" for i in range(3000))
    half = len(own) // 2
    short = license_scan.TEMPLATES["GPL-3.0"].split()
    rows = [(1, " ".join([*own[:half], filler, *own[half:]])), (2, " ".join([*short[:6], filler, *short[6:]])), (3, "Licensed under CC BY 4.0"), (4, short and " ".join(short).replace("3", "2"))]
    got = {r.doc_id: r for r in license_scan.scan_licenses(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[1].license == "ISC" and got[1].coverage == 1.0 and got[1].to_word - got[1].from_word > 3000
    assert got[2].license is None and got[3].license == "CC-BY-4.0" and got[4].license == "GPL-2.0"
    none = license_scan.scan_licenses(spark.createDataFrame(rows, "doc_id long, text string"), {})
    assert {r.license for r in none.collect()} == {None}


def test_lookup_reads_one_block():
    w = sstable.ShardWriter(block_bytes=512)
    for k in range(3000):
        w.add(sstable.key_of(k), np.arange(20, dtype="<u4").tobytes())
    data, asked = w.finish(), []

    def fetch(at, n):
        asked.append(n)
        return data[at : at + n]

    reader = sstable.ShardReader(fetch=fetch, size=len(data))
    opened = sum(asked)
    assert len(reader.get(sstable.key_of(1777))) == 1 and sum(asked) - opened < 4000 and opened < len(data)
    assert reader.get(sstable.key_of(5000)) == []


def brute_em(items):
    """Expectation-maximisation over single candidates: items are lists of votes (1, 0 or None)."""
    q = [min(0.9, max(0.1, (sum(v == 1 for v in x) + 1) / (sum(v is not None for v in x) + 2))) for x in items]
    for _ in range(100):
        prior = (sum(q) + 1) / (len(items) + 2)
        rate = []
        for j in range(len(items[0])):
            yes = sum(w for w, x in zip(q, items, strict=True) if x[j] is not None)
            no = sum(1 - w for w, x in zip(q, items, strict=True) if x[j] is not None)
            right = sum(w for w, x in zip(q, items, strict=True) if x[j] == 1)
            wrong = sum(1 - w for w, x in zip(q, items, strict=True) if x[j] == 0)
            rate.append([min(0.99, max(0.55, r)) for r in ((right + 4) / (yes + 5), (wrong + 4) / (no + 5))])
        new = []
        for x in items:
            a, b = prior, 1 - prior
            for (t, f), v in zip(rate, x, strict=True):
                a *= 1 if v is None else t if v else 1 - t
                b *= 1 if v is None else 1 - f if v else f
            new.append(a / (a + b))
        done = max(abs(x - y) for x, y in zip(q, new, strict=True)) < 1e-9
        if done:
            break
        q = new
    return q


def test_estimates_equal_plain_expectation_maximisation():
    rng = random.Random(6)
    items = ["".join(rng.choice("11-0" if truth else "00-1") for _ in range(4)) for truth in [True] * 60 + [False] * 90]
    want = dict(zip(items, brute_em([[{"1": 1, "0": 0, "-": None}[c] for c in x] for x in items]), strict=True))
    model = pii.SpanModel({})
    model.counts = {f"3|{v}|201": n for v, n in Counter(items).items()}
    got = model._estimate(3)
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-6 for k in want)


def test_secrets(spark):
    """Tokens given as values are found, long words and commit numbers are not; base kinds are as they were."""
    rng = random.Random(1)
    secret = lambda: "".join(rng.choice("0123456789abcdef") for _ in range(40))
    rows = [(i, f'some words here, token = "{secret()}" and more of them') for i in range(40)]
    rows += [(100 + i, f"see commit {secret()} of that branch") for i in range(40)]
    rows += [(200 + i, "Donaudampfschifffahrtsgesellschaftskapitaen1 " + "x" * 30) for i in range(5)]
    got = {r.doc_id: (r.pii, r.text) for r in pii.detect(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i in range(40):
        spans, t = got[i]
        assert [(s.kind, s.base, t[s.start : s.end]) for s in spans] == [(4, False, rows[i][1].split('"')[1])]
    assert not any(s.kind == 4 for i in got if i >= 100 for s in got[i][0])  # runs of digits in them may pass as base cards


def test_hot_keys_join_whole(spark):
    left = spark.createDataFrame([(1, i) for i in range(100)] + [(2, 500)] + [(9, 1)], "k long, v long").repartition(3)
    right = spark.createDataFrame([(1, 100, "a"), (2, 1, "b"), (3, 0, "c")], "k long, n long, x string")
    want = sorted([(1, i, "a") for i in range(100)] + [(2, 500, "b")])
    for hot in (7, 1000):
        assert sorted((r.k, r.v, r.x) for r in common.join_hot(left, right, "k", "n", hot).collect()) == want


def test_hash_set_collisions(monkeypatch):
    """Windows of equal hash are told apart by their words."""
    monkeypatch.setattr(decontaminate, "mixed", lambda rows: np.zeros(len(rows), np.uint64))
    s = decontaminate.WindowSet([("a", "one two three four"), ("b", "two three four five"), ("c", "nine")], 3)
    assert s.scan(b"zero two three four five".split()) == ([(1, 5)], {"a", "b"})
    assert s.scan(b"two four three".split()) == ([], set()) and s.scan([b"nine"]) == ([(0, 1)], {"c"})


@pytest.mark.parametrize("hot", [3, 1000])
def test_repeated_vectors_and_null_identifiers(spark, hot, monkeypatch):
    monkeypatch.setattr(common, "HOT", hot)
    rows = [(i, [1.0, 0.0]) for i in (5, 5, 7, None)] + [(1, [0.0, 1.0]), (None, [0.0, 0.0])]
    got = embed_dedup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sorted(map(str, ((r.vec_id, r.n_links, r.component_id) for r in got))) == sorted(map(str, [(5, 3, 5), (5, 3, 5), (7, 3, 5), (None, 3, 5), (1, 0, 1), (None, 0, None)]))


def test_joint_estimates_see_correlation():
    """Bits that go together make candidates likelier than independent ones of the same frequencies."""
    rng = np.random.default_rng(0)
    base = rng.integers(0, 2, (4000, 8))
    x = np.repeat(base, 8, axis=1).astype(float)  # eight bits, eight times each
    x = np.where(rng.random(x.shape) < 0.05, 1 - x, x)
    both = x.T @ x
    two = both / len(x)
    p = np.diag(two)
    agree = p * p + (1 - p) * (1 - p)
    one, neither = p[:, None] - two, 1 - p[:, None] - p[None, :] + two
    joint = two**2 + one**2 + one.T**2 + neither**2
    bits = list(range(8))
    d = (x[:2000][:, bits] != x[2000:][:, bits]).sum(axis=1)
    true = (d <= 1).mean()
    near, far = simhash.apart(agree, joint, bits)[:2].sum(), simhash.apart(agree, None, bits)[:2].sum()
    assert abs(near - true) < 0.2 < true - far


def test_shards_and_manifest_order(spark):
    docs = spark.createDataFrame([(i % 3, f"word {i}") for i in range(60)], "doc_id long, text string")
    manifest = sstable.write_shards(docs, scratch(spark), shard_bytes=100, n_ranges=4)
    found = sstable.lookup(manifest, [1, 77])
    assert len(found) == 20 and {k for k, _ in found} == {1}
