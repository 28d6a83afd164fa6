from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ldpspark.llm import components as comp
from ldpspark.llm import jaccard_join as jj
from ldpspark.llm import textkernel as tk

from .helpers import classes, crowded, docs, shingles, words


@settings(max_examples=60, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="aB \t\n\x0b\u00a0éz", max_size=40)), max_size=8))
def test_shingle_sets_are_those_of_the_contract(texts):
    got = [len(s) for s in tk.shingle_sets(pa.array(texts, pa.string()))]
    assert got == [len(shingles(t)) for t in texts]


def test_parity_maps_bound_the_symmetric_difference():
    rng = np.random.default_rng(1)
    for n, m, shared in ((10, 12, 5), (300, 200, 150), (1000, 1000, 900), (5, 5, 5)):
        base = rng.integers(0, 1 << 63, n + m - shared).astype(np.uint64)
        x, y = np.sort(base[:n]), np.sort(base[n - shared :])
        assert jj.apart(jj.parity(x), jj.parity(y)) <= n + m - 2 * shared


def edited(base, rng, n):
    out = list(base)
    for _ in range(n):
        out[rng.randrange(len(out))] = f"x{rng.randrange(10**6)}"
    return out


def family(seed=5):
    """Copies, near copies at all distances, chains, shared passages, short and empty texts."""
    rng = random.Random(seed)
    passage = words(60, 99)
    rows = []
    for f in range(12):
        base = words(80, f)
        rows += [" ".join(base)] * 2
        rows += [" ".join(edited(base, rng, k)) for k in (1, 1, 2, 3, 4, 5, 6)]
        chain = base
        for _ in range(4):
            chain = edited(chain, rng, 2)
            rows.append(" ".join(chain))
        rows.append(" ".join(words(20, 1000 + f) + passage))
        rows.append(" ".join(words(60, 2000 + f) + passage))
    rows += ["a b", "A  b", "a", "", None, "  \n", "a b c d e", "a b c d e f"]
    rng.shuffle(rows)
    return [(i * 3 + 1, t) for i, t in enumerate(rows)]


# rests pair by pair; parted by pivots, several levels deep; blocks only
@pytest.mark.parametrize("small, block, spread", [(jj.SMALL, jj.BLOCK, jj.SPREAD), (1, 8, 1e9), (1, 8, 0.0)])
def test_classes_are_those_of_brute_force(spark, monkeypatch, small, block, spread):
    monkeypatch.setattr(jj, "SMALL", small)
    monkeypatch.setattr(jj, "BLOCK", block)
    monkeypatch.setattr(jj, "SPREAD", spread)
    monkeypatch.setattr(jj, "LEVELS", 3)
    monkeypatch.setattr(jj, "COUNTED", 256 if small > 1 else 4)
    rows = family()
    got = {r["doc_id"]: r for r in jj.similar_classes(crowded(docs(spark, rows)), count_links=True).collect()}
    want = classes(rows)
    sets = {i: shingles(t) for i, t in rows}
    links = {i: sum(j != i and bool(x) and bool(y) and 4 * len(x & y) >= 3 * len(x | y) for j, y in sets.items()) for i, x in sets.items()}
    assert {i: r["n_links"] for i, r in got.items()} == links
    assert {i: r["component_id"] for i, r in got.items()} == want
    assert all(got[i]["n_shingles"] == len(shingles(t)) for i, t in rows)


def test_classes_hold_where_every_row_stands_twice(spark):
    rows = family()
    got = jj.similar_classes(docs(spark, rows + rows)).collect()
    assert len(got) == 2 * len(rows)
    assert {r["doc_id"]: r["component_id"] for r in got} == classes(rows)


def test_wide_regions_of_common_passages_are_parted_by_pivots(spark, monkeypatch):
    """Texts put together from a few passages: every shingle is common, and a region holds many groups far from each other."""
    monkeypatch.setattr(jj, "SMALL", 4)
    monkeypatch.setattr(jj, "COUNTED", 4)
    names = []
    monkeypatch.setattr(jj, "stage", lambda df, name, kept=jj.stage: names.append(name) or kept(df, name))
    rng = random.Random(9)
    pool = [words(25, 700 + i) for i in range(12)]
    rows = []
    for _ in range(16):
        base = sum(rng.sample(pool, 5), [])
        rows += [" ".join(edited(base, rng, rng.choice((0, 1, 2, 3, 4)))) for _ in range(6)]
    rng.shuffle(rows)
    rows = [(i, t) for i, t in enumerate(rows)]
    got = {r["doc_id"]: r for r in jj.similar_classes(docs(spark, rows), count_links=True).collect()}
    assert "level-1-parts" in names and "level-2-met" in names
    sets = {i: shingles(t) for i, t in rows}
    assert {i: r["component_id"] for i, r in got.items()} == classes(rows)
    assert {i: r["n_links"] for i, r in got.items()} == {i: sum(j != i and 4 * len(x & y) >= 3 * len(x | y) for j, y in sets.items()) for i, x in sets.items()}


def test_id_of_several_texts_is_linked_by_any(spark):
    one, two = " ".join(words(40, 61)), " ".join(words(40, 62))
    rows = [(5, one), (5, two), (8, one + " x"), (9, two + " y"), (11, " ".join(words(40, 63)))]
    got = {r["doc_id"]: r["component_id"] for r in jj.similar_classes(docs(spark, rows)).collect()}
    assert got == {5: 5, 8: 5, 9: 5, 11: 11}


def test_nulls_repeated_rows_and_empty_table(spark):
    t = " ".join(words(30, 3))
    rows = [(7, t), (7, t), (2, t), (None, t), (None, None), (9, None), (10, "")]
    got = sorted((r["doc_id"] is None, r["doc_id"] or 0, r["component_id"]) for r in jj.similar_classes(docs(spark, rows)).collect())
    assert got == [(False, 2, 2), (False, 7, 2), (False, 7, 2), (False, 9, 9), (False, 10, 10), (True, 0, None), (True, 0, None)]
    assert jj.similar_classes(docs(spark, [])).count() == 0
    kept = jj.one_per_class(docs(spark, rows))
    assert sorted(r["doc_id"] or -1 for r in kept.collect()) == [-1, -1, 2, 9, 10]
    assert kept.columns == ["doc_id", "text", "lang", "source", "n_chars"]


def test_one_very_long_text(spark):
    long = words(60_000, 8, 10**6)
    rows = [(1, " ".join(long)), (2, " ".join(long[:50_000])), (3, " ".join(long[:40_000])), (4, "short")]
    got = {r["doc_id"]: r["component_id"] for r in jj.similar_classes(docs(spark, rows)).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4}


def test_components_of_chains_stars_and_loops(spark):
    links = [(i, i + 1) for i in range(1, 40)] + [(100, x) for x in range(101, 140)] + [(500, 500), (None, 3), (200, 201), (201, 200)]
    got = {r["node"]: r["component"] for r in comp.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {**{i: 1 for i in range(1, 41)}, **{x: 100 for x in range(100, 140)}, 500: 500, 200: 200, 201: 200}
    assert comp.components(spark.createDataFrame([], "a long, b long")).count() == 0
