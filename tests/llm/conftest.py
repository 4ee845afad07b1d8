from __future__ import annotations

import random

import pytest

SF = "/root/testdata/sf0.001"
KIND = "doc_id long, text string, lang string, source string, n_chars long, Score double, FP string, _quality int, n_hit string, _found string, `odd name.x` int"


def filler(rng: random.Random, n: int) -> str:
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 8))) for _ in range(n))


def make_docs() -> list[tuple]:
    """Nulls in every column, empty, blank, very long and repeated texts, ties, copies near and exact, odd characters."""
    rng = random.Random(11)
    base = filler(rng, 120)
    words = base.split()
    near = " ".join([*words[:60], "changed", *words[61:]])
    texts = [
        None, "", "   \n\t ", base, base, near, base.upper(), filler(rng, 4000), "a", "a b c", "!!! ### $$$", "été Straße 😀 x\x1cy ١٢", "x" * 30_000, filler(rng, 300), "\u3000全角 文字 列",
        "write to jo.hn@mail.example.com or call +1 (555) 010-9999, ip 10.20.30.40, card 4111 1111 1111 1111.", "Licensed under the Apache License, Version 2.0.", "<|endoftext|> it's 'S don't", base + " tail",
    ]
    rows = [(i, t, ["en", "de", None][i % 3], "s", len(t or ""), 0.5, "z", 7, "q", "f", i) for i, t in enumerate(texts)]
    rows.append(rows[3])  # a repeated row
    rows.append((None, filler(rng, 50), None, None, None, None, None, None, None, None, None))
    rows.append((None, None, None, None, None, None, None, None, None, None, None))
    return rows


@pytest.fixture(scope="session")
def docs(spark):
    return spark.createDataFrame(make_docs(), KIND).repartition(3)


@pytest.fixture(scope="session")
def no_docs(spark):
    return spark.createDataFrame([], KIND)
