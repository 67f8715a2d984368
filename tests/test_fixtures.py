"""Golden values of FIXTURES.md, and the behaviour that the experiments are expected to show."""

import os

import pytest
from pyspark.sql import functions as F

from blockdelta import catalogue, workloads
from blockdelta.functions import costmodel
from blockdelta.operators import blocks, containers, gather, regions, tracker
from blockdelta.plans import metrics
from blockdelta.session import settled

SF = "/root/testdata/sf0.01"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables are not here")


def share(states):
    r = metrics.dirty_share(states).first()
    return r["n_blocks"], r["n_written"]


def test_wave_without_ranks(spark):
    want = {128: (625, 21), 256: (313, 11), 512: (157, 6), 1024: (79, 3), 2048: (40, 2), 4096: (20, 2), 8192: (10, 2), 16384: (5, 1), 32768: (3, 1)}
    assert {b: share(catalogue.wave_states(spark, SF, b, ranks=1)) for b in want} == want


@pytest.mark.parametrize("sf,want", [("sf0.001", (64, 3, 2, 2, 376)), ("sf0.01", (640, 23, 2, 2, 2824)), ("sf0.1", (6256, 218, 2, 2, 27856))])
def test_wave_with_ranks(spark, sf, want):
    states = settled(catalogue.wave_states(spark, f"/root/testdata/{sf}").drop("digest"))
    merged = regions.merge(states, 128).agg(F.countDistinct("rank").alias("ranks"), F.count(F.lit(1)).alias("n"), F.sum("n_bytes").alias("bytes")).first()
    assert (*share(states), merged["ranks"], merged["n"], merged["bytes"]) == want


def test_scatter(spark):
    before, after = (settled(workloads.scatter(spark, SF, d)) for d in catalogue.WEEK)
    want = {128: (3750, 164), 512: (938, 149), 2048: (235, 118), 8192: (59, 55)}
    assert {b: share(catalogue.states_of(before, after, b)) for b in want} == want


def test_series(spark):
    plan = containers.plan(workloads.series_sizes(spark, SF, catalogue.DAYS)).groupBy("born_version").agg(F.count(F.lit(1)).alias("n"), F.sum("container_bytes").alias("b"))
    assert [(r["n"], r["b"]) for r in plan.orderBy("born_version").collect()] == [(150, 10896), (150, 12920), (150, 26808), (150, 26744)]
    sizes = settled(workloads.series_sizes(spark, SF, catalogue.DAYS, 7))
    plan = containers.plan(sizes)
    assert [r["count"] for r in plan.groupBy("born_version").count().orderBy("born_version").collect()] == [150, 132, 74, 47]
    sparse = metrics.sparsity(containers.fill(plan, sizes)).orderBy("version").collect()
    assert [(r["capacity"], r["live"]) for r in sparse] == [(10896, 10896), (18280, 18192), (21232, 18616), (22640, 18688)]


def test_ladder_is_exact():
    assert [sum(k * 37 % 100 < p for k in range(3700)) for p in (99, 95, 87, 79, 71, 63, 56, 40)] == [3663, 3515, 3219, 2923, 2627, 2331, 2072, 1480]


def test_heat_spreads(spark):
    want, grid, previous = {1: 54, 2: 91, 5: 201}, settled(workloads.heat_start(spark, SF)), 0
    before = grid
    for t in range(1, 6):
        grid = settled(workloads.heat_step(grid))
        if t in want:
            changed = F.size(F.filter(F.zip_with("xs", "ys", lambda x, y: x != y), lambda c: c))
            both = grid.join(before.select("row", F.col("xs").alias("ys")), "row").agg((F.sum(changed) * 1000 / F.sum(F.size("xs"))).alias("s")).first()["s"]
            assert abs(both - want[t]) < 1
            before = grid


def test_turns_and_documents(spark):
    turns = spark.read.parquet(f"{SF}/conversations.parquet")
    assert [turns.where(F.col("turn") <= k).count() for k in range(8)] == [100, 200, 292, 370, 436, 487, 517, 536]
    cut = catalogue.QUERIES["text_blocks"](spark, SF)
    assert (cut.count(), cut.select("digest").distinct().count()) == (2940, 2739)


def test_write_rate_grows_with_block_size(spark):
    rates = {r["b"]: r["byte_ppm"] for r in catalogue.QUERIES["block_sweep_scatter"](spark, SF).collect()}
    ordered = [rates[b] for b in sorted(rates)]
    assert ordered == sorted(ordered)
    pieces = {r["b"]: r["n_regions"] for r in catalogue.QUERIES["region_sweep_plasma"](spark, SF).collect()}
    assert pieces[32768] <= pieces[128]


def test_exposure_and_layout(spark):
    rows = {r["variant"]: r["block_ppm"] for r in catalogue.QUERIES["plasma_grid"](spark, SF).collect()}
    assert abs(rows["A_many_column"] - 500_000) < 10_000 and abs(rows["B_one_column"] - 625_000) < 10_000
    assert rows["A_one_row"] == rows["B_one_row"] == 1_000_000
    small, large = (metrics.chunk_quantiles(regions.merge(catalogue.plasma_states(spark, SF, c, "one", b=128), 128)).first()["q50"] for c in "AB")
    assert large > 10 * small


def test_gathering_saves_writes(spark):
    merged = settled(regions.merge(catalogue.plasma_states(spark, SF, "A", "one", b=128), 128))
    packed = gather.units(gather.pack(merged, 8192))
    assert packed.count() < merged.count()
    assert packed.agg(F.sum("unit_bytes")).first()[0] == merged.agg(F.sum("n_bytes")).first()[0]
    last = {r["rank"]: r["u"] for r in packed.groupBy("rank").agg(F.max("unit_no").alias("u")).collect()}
    assert all(r["unit_bytes"] > 8192 for r in packed.collect() if r["unit_no"] < last[r["rank"]])


def test_hot_rank_explains_the_model_error(spark):
    skew = catalogue.QUERIES["rank_skew"](spark, SF).first()
    assert skew["rank"] == 0 and skew["most_ppm"] > 10 * skew["mean_ppm"] - 100_000
    low, high = costmodel.speedup_bounds(skew["mean_ppm"] / 1e6, skew["most_ppm"] / 1e6, 0.029)
    assert low < -0.8 < high


def test_no_strong_digest_misses_a_change(spark):
    assert all(r["n_missed"] == 0 and r["n_changed"] > 0 for r in catalogue.QUERIES["false_clean"](spark, SF).collect())


def test_relocation(spark):
    rows = {(r["tracked_by"], r["status"]): r["n"] for r in catalogue.QUERIES["relocation"](spark, SF).collect()}
    assert rows.get(("dataset", "dirty"), 0) == 0 and rows["address", "dirty"] > 0.4 * sum(n for (t, _), n in rows.items() if t == "address")


def test_empty_state(spark):
    none = spark.createDataFrame([], "rank int, dataset_id string, pos bigint, cell bigint")
    states = tracker.classify(blocks.cut(none, 64), tracker.create_ledger(blocks.cut(none, 64)))
    assert states.count() == 0 and regions.merge(states, 64).count() == 0
