"""Blocks, regions, containers, gathering on worked cases."""

import pytest
from pyspark.sql import functions as F

from blockdelta import catalogue, workloads
from blockdelta.operators import blocks, containers, gather, levels, protect, regions, tracker
from blockdelta.plans import baselines


def cells(spark, values, rank=0, dataset="d"):
    return spark.createDataFrame([(rank, dataset, k, v) for k, v in enumerate(values)], "rank int, dataset_id string, pos bigint, cell bigint")


def status(states):
    return {r["block_no"]: r["status"] for r in states.collect()}


def test_cut_edges(spark):
    assert blocks.cut(cells(spark, []), 16).count() == 0
    assert [r["block_len"] for r in blocks.cut(cells(spark, [1]), 16).collect()] == [8]
    assert sorted(r["block_len"] for r in blocks.cut(cells(spark, [1, -2, 3, -(1 << 63)]), 16).collect()) == [16, 16]
    assert sorted(r["block_len"] for r in blocks.cut(cells(spark, [1, 2, 3]), 16).collect()) == [8, 16]
    with pytest.raises(ValueError):
        blocks.cut(cells(spark, [1]), 12)
    back = blocks.uncut(blocks.cut(cells(spark, [1, -2, 3, -(1 << 63), (1 << 63) - 1]), 16), 16)
    assert [r["cell"] for r in back.orderBy("pos").collect()] == [1, -2, 3, -(1 << 63), (1 << 63) - 1]


def test_clustered_cut_is_the_same(spark):
    values = [(7 * k * k - 50) for k in range(45)]
    arrays = spark.createDataFrame([(0, "d", 0, values[:32]), (0, "d", 32, values[32:])], "rank int, dataset_id string, start bigint, cells array<bigint>")
    want = {(r["block_no"], bytes(r["payload"])) for r in blocks.cut(cells(spark, values), 64).collect()}
    assert {(r["block_no"], bytes(r["payload"])) for r in blocks.cut_clustered(arrays, 64).collect()} == want


def test_states(spark):
    old, new = cells(spark, [1, 2, 3, 4, 5]), cells(spark, [1, 2, 3, 9, 5, 6, 7])
    ledger = tracker.create_ledger(blocks.cut(old, 16))
    assert status(tracker.classify(blocks.cut(new, 16), ledger)) == {0: "clean", 1: "dirty", 2: "invalid", 3: "invalid"}
    assert status(tracker.classify(blocks.cut(cells(spark, [1, 2, 3]), 16), ledger)) == {0: "clean", 1: "invalid", 2: "retired"}
    states = tracker.classify(blocks.cut(new, 16), ledger)
    after = tracker.advance(ledger, states, "md5", 2)
    assert {r["block_no"]: r["version"] for r in after.collect()} == {0: 0, 1: 2, 2: 2, 3: 2}
    assert set(status(tracker.classify(blocks.cut(new, 16), after)).values()) == {"clean"}
    with pytest.raises(ValueError):
        tracker.check_ledger(ledger, "crc32", 16)


def test_regrown_blocks_are_new(spark):
    long, short = cells(spark, [1, 2, 3, 4]), cells(spark, [1, 2])
    ledger = tracker.create_ledger(blocks.cut(long, 16))
    ledger = tracker.advance(ledger, tracker.classify(blocks.cut(short, 16), ledger), "md5", 2)
    assert status(tracker.classify(blocks.cut(long, 16), ledger)) == {0: "clean", 1: "invalid"}


def given_states(spark, letters, b=8, size=None):
    names = {"C": "clean", "D": "dirty", "I": "invalid", "R": "retired"}
    rows = [(0, "d", k, min(b, (size or b * len(letters)) - k * b), names[c]) for k, c in enumerate(letters)]
    return spark.createDataFrame(rows, "rank int, dataset_id string, block_no bigint, block_len bigint, status string")


@pytest.mark.parametrize("stride", [None, 1, 2, 4])
def test_regions(spark, stride):
    got = regions.merge(given_states(spark, "CDDICD", size=45), 8, stride).orderBy("region_no").collect()
    assert [(r["start_byte"], r["n_bytes"], r["n_blocks"], r["n_invalid"]) for r in got] == [(8, 24, 3, 1), (40, 5, 1, 0)]
    assert regions.merge(given_states(spark, "CCCR"), 8, stride).count() == 0
    assert [r["n_blocks"] for r in regions.merge(given_states(spark, "DDDD"), 8, stride).collect()] == [4]
    assert list(regions.iter_regions(given_states(spark, "DCD"), 8)) == [(0, "d", 0, 8), (0, "d", 16, 8)]


def test_containers(spark):
    sizes = spark.createDataFrame([(0, "d", v + 1, s) for v, s in enumerate((100, 160, 120, 200))], "rank int, dataset_id string, version int, size_bytes bigint")
    plan = containers.plan(sizes)
    assert [(r["born_version"], r["container_bytes"], r["virtual_start"]) for r in plan.orderBy("container_no").collect()] == [(1, 100, 0), (2, 60, 100), (4, 40, 160)]
    placed = containers.place(plan, 10)
    assert [r["file_offset"] for r in placed.orderBy("container_no").collect()] == [10, 120, 190]
    filled = containers.fill(plan, sizes)
    assert {(r["version"], r["container_no"]): r["chunk_bytes"] for r in filled.collect()}[3, 2] == 20
    region = spark.createDataFrame([(0, "d", 1, 90, 40)], "rank int, dataset_id string, region_no int, start_byte bigint, n_bytes bigint")
    assert sorted((r["container_no"], r["file_offset"], r["n_bytes"]) for r in containers.extents(region, placed).collect()) == [(1, 100, 10), (2, 120, 30)]


@pytest.mark.parametrize("mode", ["greedy", "cutline"])
def test_gather(spark, mode):
    rows = [(0, "d", k, 0, n, 1, 0) for k, n in enumerate((5, 7, 3, 20, 1))]
    df = spark.createDataFrame(rows, "rank int, dataset_id string, region_no int, start_byte bigint, n_bytes bigint, n_blocks bigint, n_invalid bigint")
    sizes = [r["unit_bytes"] for r in gather.units(gather.pack(df, 10, mode)).orderBy("unit_no").collect()]
    assert sum(sizes) == 36
    if mode == "greedy":
        assert sizes == [12, 23, 1]


def test_parity(spark):
    a, b = cells(spark, [1, 2, 3], 0), cells(spark, [5, 6], 1)
    lost = levels.rebuild(levels.parity(a.union(b), 4), a, 1, 4, spark.createDataFrame([("d", 2)], "dataset_id string, n_cells bigint"))
    assert [r["cell"] for r in lost.orderBy("pos").collect()] == [5, 6]
    with pytest.raises(ValueError):
        levels.post_process(a, 5)
    assert set(levels.post_process(a, 2)) == {"replica"} and levels.post_process(a, 1) == {}


def test_positions_must_differ(spark):
    with pytest.raises(ValueError):
        protect.check_positions(cells(spark, [1, 2]).union(cells(spark, [3])))
    protect.check_positions(cells(spark, [1, 2]))


def test_pages_by_address_move(spark):
    before = cells(spark, range(4), dataset="a").union(cells(spark, range(8), dataset="b"))
    after = cells(spark, range(6), dataset="a").union(cells(spark, range(8), dataset="b"))
    assert set(status(baselines.page_hash(baselines.address_space(before), baselines.address_space(after), 16)).values()) > {"dirty"}
    assert "dirty" not in set(r["status"] for r in tracker.classify(blocks.cut(after, 16), tracker.create_ledger(blocks.cut(before, 16))).collect())


def test_numbering_is_dense(spark):
    from blockdelta import workloads

    df = spark.range(1000).selectExpr("(id * 37) % 1000 AS k")
    assert [(r["k"], r["number"]) for r in workloads.numbered(df, ["k"], 8).orderBy("k").collect()] == [(k, k) for k in range(1000)]


PLASMA = {"_".join(g): g for g in catalogue.GRID}


@pytest.mark.parametrize("name", list(PLASMA))
def test_packed_runs_give_the_states_of_the_ledger(spark, sf_dir, name):
    """Blocks that straddle runs, columns and groups, short last ones, and several sizes cut at once."""
    config, expose, layout = PLASMA[name]
    cells = [workloads.plasma(spark, sf_dir, s, config, expose, layout) for s in (0, 1)]
    columns = ["rank", "dataset_id", "block_no", "block_len", "status"]
    for sizes in ([128], [1024], [128, 1024]):
        found = catalogue.plasma_sweep(spark, sf_dir, config, expose, sizes, layout)
        for b in sizes:
            expected = catalogue.states_of(*cells, b).select(*columns).collect()
            assert sorted(map(repr, found.where(F.col("b") == b).select(*columns).collect())) == sorted(map(repr, expected))


@pytest.mark.parametrize("name", ["chunk_cdf", "fragmentation", "block_sweep_plasma", "region_sweep_plasma", "plasma_grid"])
def test_plasma_queries_move_no_single_cells(spark, sf_dir, monkeypatch, name):
    """Cells of the stacked plasma state are not made one by one."""
    monkeypatch.setattr(workloads, "plasma", lambda *a, **b: pytest.fail("cells one by one"))
    catalogue.QUERIES[name](spark, sf_dir)
