from __future__ import annotations

import corpus_pipeline as cp
import pytest
from pyspark.sql import functions as F

from ldpspark.llm import mixing, quality
from ldpspark.llm import queries as llm_queries

from .helpers import CROWD, SF, classes, crowded
from .test_text_filters import brute_hits


@pytest.fixture(scope="module")
def steps(spark):
    out = [spark.read.parquet(f"{SF}/documents.parquet")]
    for _, work in cp.STAGES:
        out.append(work(spark, out[-1], SF).persist())
    return out


def ids(df):
    return sorted(r["doc_id"] for r in df.select("doc_id").collect())


def test_each_stage_equals_brute_force_on_its_own_input(spark, steps):
    first, kept, apart, clean, mix, shards = steps
    assert all(s.columns == first.columns for s in steps[:-1])
    score = {r["doc_id"]: r["predicted"] for r in quality.quality_scores(first, spark.read.parquet(f"{SF}/labels.parquet")).collect()}
    assert ids(kept) == sorted(i for i, p in score.items() if p)
    want = classes([(r["doc_id"], r["text"]) for r in kept.collect()])
    assert ids(apart) == sorted(i for i, c in want.items() if i == c)
    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    assert ids(clean) == sorted(x[0] for x in brute_hits([(r["doc_id"], r["text"]) for r in apart.collect()], items) if not x[-1])
    copies = {r["doc_id"]: r["copies"] for r in mixing.mixed(clean).collect()}
    assert {r["doc_id"]: r["count"] for r in mix.groupBy("doc_id").count().collect()} == {i: c for i, c in copies.items() if c}
    assert ids(shards) == ids(mix)
    counts = [r["count"] for r in shards.groupBy("shard").count().collect()]
    assert max(counts) - min(counts) <= 1


def test_run_gives_the_last_stage(spark, steps):
    got = cp.run(spark, SF)
    assert sorted(map(str, got.select("doc_id", "shard", "slot").collect())) == sorted(map(str, steps[-1].select("doc_id", "shard", "slot").collect()))


def test_stages_bear_an_empty_table(spark):
    empty = spark.read.parquet(f"{SF}/documents.parquet").where(F.lit(False))
    for _, work in cp.STAGES:
        empty = work(spark, empty, SF)
        assert empty.count() == 0


def test_stages_keep_columns_whose_names_are_used_inside(spark):
    names = [*CROWD, "shard", "slot", "copy_number"]
    full = crowded(spark.read.parquet(f"{SF}/documents.parquet")).withColumns({c: F.lit(-9) for c in names})
    for name, work in cp.STAGES:
        out = work(spark, full, SF)
        kept = [c for c in full.columns if c not in ("shard", "slot")] + ["shard", "slot"] if name == "sharding" else full.columns
        assert out.columns == kept
        odd = [c for c in names if c not in ("shard", "slot")]
        assert out.where(" or ".join(f"`{c}` != -9 or `{c}` is null" for c in odd)).count() == 0
        assert out.count() > 100


def test_ten_queries_are_registered():
    numbers = sorted(int(name[2:].split("_")[0]) for name in llm_queries.QUERIES)
    assert numbers == list(range(1, 11))
