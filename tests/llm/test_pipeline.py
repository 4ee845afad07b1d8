"""The pipeline against a plain version of every stage, on whole tables."""

from __future__ import annotations

import random
import zlib

import numpy as np
import xxhash
from test_operators import brute_hits, check_packing, union
from tokenizers import Tokenizer

import corpus_pipeline
from standq.llm import pii, quality_mil, simhash, simhash_verified, tokens

SF = "/root/testdata/sf0.001"


def test_stages(spark):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "simhash near-dedup", "benchmark decontamination", "pii", "best-fit packing"]
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    rows = {r.doc_id: r.text for r in docs.collect()}
    model = quality_mil.train(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    rows = {i: t for i, t in rows.items() if model.score([quality_mil.features(t or "")])[0] >= 0.5}
    rows = {i: rows[i] for i in brute_dissimilar(sorted(rows.items()))[0]}
    bench = [tuple(r) for r in spark.read.parquet(f"{SF}/benchmark.parquet").select("item_id", "text").collect()]
    rows = {i: t for i, t in rows.items() if not brute_hits(t, bench)[1]}
    engine, want = Tokenizer.from_file(tokens.public_path()), []
    for i, t in rows.items():
        out, at = [], 0
        for s, k, e in pii.base_spans(t):  # these texts hold no other spans
            if s >= at:
                out += [t[at:s], f"[{pii.KINDS[k].upper()}]"]
            at = max(at, e)
        ids = [*engine.encode("".join([*out, t[at:]]), add_special_tokens=False).ids, 0]
        want += [(i, n, zlib.crc32(np.array(ids[p : p + 2048], "<u4").tobytes())) for n, p in enumerate(range(0, len(ids), 2048))]
    got = corpus_pipeline.run(spark, SF).collect()
    check_packing(got, 2048)
    assert sorted(want) == sorted((r.doc_id, r.piece, r.ids_crc32) for r in got)


def test_columns_stay(spark, docs):
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        docs = out.select("*")


def brute_words(t):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "").encode().split()


def brute_print(shingles):
    """128 majority bits of the hashes and a remix, with plain numbers."""
    h, out, most = [xxhash.xxh64_intdigest(b" ".join(x), 42) for x in shingles], 0, (1 << 64) - 1
    for k in range(2):
        mixed = []
        for v in h:
            if k:
                v = (v + k * 0x9E3779B97F4A7C15) & most
                v = ((v ^ v >> 30) * 0xBF58476D1CE4E5B9) & most
                v = ((v ^ v >> 27) * 0x94D049BB133111EB) & most
                v ^= v >> 31
            mixed.append(v)
        out |= sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in mixed) > len(h)) << 64 * k
    return out


def brute_dissimilar(rows, words=5, by_print=False):
    """Identifiers kept of (id, text): all pairs of whole shingle sets, Jaccard 0.8 or more (and near fingerprints)."""
    sets = []
    for _, t in rows:
        w = brute_words(t)
        sets.append({tuple(w[i : i + words]) for i in range(max(1, len(w) - words + 1))} if w else set())
    near = [(i, j) for i, x in enumerate(sets) for j, y in enumerate(sets[:i]) if min(len(x), len(y)) >= 0.8 * max(len(x), len(y)) and 5 * len(x & y) >= 4 * len(x | y)]
    if by_print:
        prints = [brute_print(x) for x in sets]
        apart = [prints[i] ^ prints[j] for i, j in near]
        near = [p for p, x in zip(near, apart, strict=True) if x.bit_count() <= simhash_verified.TAU]
    root = union(len(rows), near)
    kept = {}
    for (i, _), r in zip(rows, root, strict=True):
        kept[r] = min(i, kept.get(r, i))
    return sorted(kept.values()), near


def test_near_copies_of_the_stage(spark, monkeypatch):
    """Copies planted at similarities around 0.8 to 0.95, under a frequent heading, beside chance ones; one large group."""
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    head, rows = "this text may be used and copied by anybody who keeps this notice with it", []
    for n in range(60):
        base = [word() for _ in range(rng.choice([8, 40, 200, 600]))]
        rows += [(7 * n, " ".join([head, *base])), (7 * n + 1, " ".join([head.upper(), *base]))]
        for k in range(2, 7):
            other = list(base)
            for _ in range(rng.randint(1, 1 + len(base) // 50)):
                other[rng.randrange(len(base))] = word()
            rows.append((7 * n + k, " ".join([head, *other])))
    base = [word() for _ in range(300)]
    for n in range(150):
        other = list(base)
        for _ in range(3):
            other[rng.randrange(300)] = word()
        rows.append((2000 + n, " ".join(other)))
    rows += [(1000, None), (1001, " "), (1002, "a b"), (1003, "A  b"), (1004, "a b c")]
    want, near = brute_dissimilar(rows, by_print=True)
    every, all_near = brute_dissimilar(rows)
    assert len(all_near) > 2000 and len(near) >= 0.98 * len(all_near)
    assert set(every) <= set(want) and len(want) - len(every) <= 2  # nothing goes that has no near text; hardly one stays that has
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(r.doc_id for r in corpus_pipeline.near_dedup(spark, docs, SF).collect()) == want
    for name, small in (("FEW", 0), ("BLOCK", 20), ("ROWS", 60), ("TILE", 3)):
        monkeypatch.setattr(simhash_verified, name, small)
    assert sorted(r.doc_id for r in simhash_verified.keep_dissimilar(docs).collect()) == want
    assert simhash.keep_one(docs).count() > len(want)  # the rule of op7 is narrower


def test_texts_of_a_large_group_move_a_few_times(spark, monkeypatch):
    """Few of a large group of near copies are unconnected after the first pairs; the others go to the tasks about once."""
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    base, rows = [word() for _ in range(300)], []
    for n in range(400):
        other = list(base)
        for _ in range(3 if n % 40 else 12):
            other[rng.randrange(300)] = word()
        rows.append((n, " ".join(other)))
    moved, put = {}, simhash_verified.staged

    def staged(df, name):
        out = put(df, name)
        moved[name] = out.count()
        return out

    monkeypatch.setattr(simhash_verified, "staged", staged)
    monkeypatch.setattr(simhash_verified, "TILE", 20)
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert sorted(r.doc_id for r in simhash_verified.keep_dissimilar(docs).collect()) == brute_dissimilar(rows, by_print=True)[0]
    assert moved.get("again", 0) <= 8 * len(rows)


def test_classes_move_once_a_tile(spark):
    """At 2.8 million classes (6 GB of documents) a class is filed seven or eight times; by blocks of bits it was some 470."""
    classes = spark.range(50).selectExpr("id AS key", "id AS w0", "id AS w1")
    assert simhash_verified.dealt(classes, 2_800_000).count() <= 8 * 50
    met = {tuple(sorted((a.key, b.key))) for rows in by_bucket_of(simhash_verified.dealt(classes, 400)) for a in rows for b in rows if a.key != b.key}
    assert len(met) == 50 * 49 // 2


def by_bucket_of(dealt):
    out = {}
    for r in dealt.collect():
        out.setdefault(r.bucket, []).append(r)
    return out.values()
