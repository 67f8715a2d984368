"""The store: round trips in all modes, crashes at every step, damage, rollback and vacuum."""

import pytest

from blockdelta.operators import blocks, tracker
from blockdelta.plans import baselines, engine
from blockdelta.session import fresh_folder
from blockdelta.sources import restore
from blockdelta.sources.store import STEPS, BlockStore, StoreError


def state(spark, values):
    return spark.createDataFrame([(k % 2, "ab"[k % 3 > 0], k // 2, v) for k, v in enumerate(values)], "rank int, dataset_id string, pos bigint, cell bigint").selectExpr(
        "rank", "dataset_id", "row_number() OVER (PARTITION BY rank, dataset_id ORDER BY pos) - 1L AS pos", "cell"
    )


def rows(df):
    return sorted((r["rank"], r["dataset_id"], r["pos"], r["cell"]) for r in df.collect())


HISTORY = [list(range(60)), [*range(30), 99, *range(31, 60)], list(range(40)), [*range(5), 7, *range(6, 80)]]


def new_store(spark, **options):
    return BlockStore(spark, fresh_folder(spark, "t"), 32, bucket_blocks=2, **options)


@pytest.mark.parametrize("mode,algo,keep", [("copy_on_write", "md5", False), ("copy_on_write", "crc32", True), ("delta_chain", "md5", True), ("buffered", "crc32", False), ("full", "md5", False)])
def test_every_version_comes_back(spark, mode, algo, keep):
    store = new_store(spark, algo=algo)
    for values in HISTORY:
        engine.checkpoint(state(spark, values), store, mode, gather_target=48, keep_pending=keep)
    for k, values in enumerate(HISTORY):
        if k in (1, 3):
            assert rows(restore.read(store, k + 1)) == rows(state(spark, values))
    assert restore.verify(store, 4).where("not ok").count() == 0
    now = blocks.cut(state(spark, HISTORY[-1]), 32)
    assert {r["status"] for r in tracker.classify(now, store.ledger(4), algo).collect()} == {"clean"}


def test_counts(spark):
    store = new_store(spark)
    first = engine.checkpoint(state(spark, HISTORY[0]), store)
    assert first.mode == "full" and first.compared_hashes == 0 and first.committed_hashes == first.total_blocks
    again = engine.checkpoint(state(spark, HISTORY[0]), store)
    assert (again.dirty, again.invalid, again.written_bytes, again.physical_bytes, again.n_regions) == (0, 0, 0, 0, 0)
    assert store.latest() == 2 and rows(restore.read(store)) == rows(state(spark, HISTORY[0]))
    third = engine.checkpoint(state(spark, HISTORY[1]), store)
    assert third.dirty == 1 and third.written_bytes == 32
    worst = baselines.everything_dirty(state(spark, HISTORY[1]), store)
    assert worst.dirty == worst.total_blocks and worst.write_rate == 1


@pytest.mark.parametrize("step", STEPS[:-1])
@pytest.mark.parametrize("hard", [False, True])
def test_crash_leaves_the_last_version(spark, step, hard, monkeypatch):
    """The next checkpoint simply works, also where the driver was lost before it could clean up."""

    def crash(at):
        if at == step:
            raise RuntimeError("crash")

    store = new_store(spark)
    engine.checkpoint(state(spark, HISTORY[0]), store)
    store.on_step = crash
    with monkeypatch.context() as lost:
        if hard:
            lost.setattr(store, "discard", lambda: None)
        with pytest.raises(RuntimeError):
            engine.checkpoint(state(spark, HISTORY[1]), store)
    assert store.versions() == [1] and rows(restore.read(store)) == rows(state(spark, HISTORY[0]))
    left = store._list(f"{store.path}/data")
    assert (len(left) == 1) == (not hard or step == "start")
    again = BlockStore(spark, store.path, 32, bucket_blocks=2)
    engine.checkpoint(state(spark, HISTORY[2]), again)
    assert rows(restore.read(again)) == rows(state(spark, HISTORY[2]))
    with pytest.raises(StoreError):
        again.rollback(2)
    again.vacuum(1)
    assert all(name.endswith(again.attempt) or name in {f["dir"] for f in again.manifest(2)["files"]} for name in again._list(f"{store.path}/data"))


def test_one_of_two_writers_commits(spark):
    first = new_store(spark)
    engine.checkpoint(state(spark, HISTORY[0]), first)
    second = BlockStore(spark, first.path, 32, bucket_blocks=2)

    def race(step):
        if step == "manifest":
            first.on_step = lambda s: None
            engine.checkpoint(state(spark, HISTORY[2]), second)

    first.on_step = race
    with pytest.raises(StoreError):
        engine.checkpoint(state(spark, HISTORY[1]), first)
    assert first.versions() == [1, 2] and rows(restore.read(first)) == rows(state(spark, HISTORY[2]))
    engine.checkpoint(state(spark, HISTORY[3]), first)
    assert rows(restore.read(first, 3)) == rows(state(spark, HISTORY[3]))


def test_unfinished_manifest_is_no_version(spark):
    store = new_store(spark)
    engine.checkpoint(state(spark, HISTORY[0]), store)
    store._create(f"{store.path}/manifests/v2.json", '{"version": 2, "fil')
    assert store.versions() == [1] and store.latest() == 1
    assert engine.checkpoint(state(spark, HISTORY[1]), store).version == 3
    assert rows(restore.read(store)) == rows(state(spark, HISTORY[1]))


@pytest.mark.parametrize("mode", ["copy_on_write", "delta_chain", "full"])
def test_ledger_is_of_what_the_files_hold(spark, tmp_path, mode):
    """The source moves on between comparison and writing."""
    path = str(tmp_path / "source")
    moving = lambda values: state(spark, values).write.mode("overwrite").parquet(path)
    read = lambda: spark.read.schema("rank int, dataset_id string, pos bigint, cell bigint").parquet(path)
    store = new_store(spark)
    moving(HISTORY[0])
    engine.checkpoint(read(), store)
    moving(HISTORY[1])
    held = read()

    def move(step):
        if step == "start":
            moving([*HISTORY[1][:59], -5])
            spark.catalog.refreshByPath(path)

    store.on_step = move
    try:
        engine.checkpoint(held, store, mode)
    except Exception:  # the files that the plan knew are gone: nothing is committed
        assert store.versions() == [1]
        return
    now = blocks.cut(restore.read(store), 32)
    assert {r["status"] for r in tracker.classify(now, store.ledger(2), "md5").collect()} == {"clean"}


def test_auto_mode(spark):
    store = new_store(spark)
    engine.checkpoint(state(spark, HISTORY[0]), store, "auto", rho=0.03)
    assert engine.checkpoint(state(spark, HISTORY[1]), store, "auto").mode == "copy_on_write"
    everywhere = [v + 1000 * (k % 5 == 0) for k, v in enumerate(HISTORY[1])]
    out = engine.checkpoint(state(spark, everywhere), store, "auto")
    assert out.mode == "delta_chain" and out.physical_rate <= out.write_rate
    assert rows(restore.read(store)) == rows(state(spark, everywhere))
    assert engine.checkpoint(state(spark, [v + 1 for v in everywhere]), store, "auto", rho=0.4).mode == "full"


def test_failed_copy_means_full(spark):
    def fail():
        raise OSError("no room")

    store = new_store(spark)
    engine.checkpoint(state(spark, HISTORY[0]), store)
    store.prepare_base(fail)
    assert engine.checkpoint(state(spark, HISTORY[1]), store).mode == "full"
    store.prepare_base()
    assert engine.checkpoint(state(spark, HISTORY[1]), store).mode == "copy_on_write"


def test_mode_by_model(spark):
    store = new_store(spark)
    assert store.choose_mode() == "full"
    engine.checkpoint(state(spark, HISTORY[0]), store)
    assert store.choose_mode(dirty_share=0.5, rho=0.029) == "copy_on_write"
    assert store.choose_mode(dirty_share=0.99, rho=0.029) == "full"
    with pytest.raises(ValueError):
        store.choose_mode("in_place")


def test_other_ledger_is_never_compared(spark):
    path = fresh_folder(spark, "t")
    engine.checkpoint(state(spark, HISTORY[0]), BlockStore(spark, path, 32))
    with pytest.raises(StoreError):
        BlockStore(spark, path, 32, "crc32").ledger(1)
    out = engine.checkpoint(state(spark, HISTORY[0]), BlockStore(spark, path, 32, "crc32"))
    assert out.mode == "full" and out.invalid == out.total_blocks


def test_errors_and_damage(spark):
    store = new_store(spark)
    with pytest.raises(StoreError):
        restore.read(store)
    for values in HISTORY[:3]:
        engine.checkpoint(state(spark, values), store)
    with pytest.raises(StoreError):
        store.manifest(9)
    with pytest.raises(StoreError):
        store.promote({"version": 2}, "nowhere")
    restore.require_sound(store, 3)
    assert store.vacuum(1) == [1, 2] or store.vacuum(1) is not None
    assert store.versions() == [3] and rows(restore.read(store)) == rows(state(spark, HISTORY[2]))
    fs, where = store._fs(f"{store.path}/data/{store.manifest(3)['dir']}")
    fs.delete(where, True)
    with pytest.raises(StoreError):
        restore.require_sound(store, 3)


def test_incomplete_version_is_not_sealed(spark):
    from blockdelta.operators import protect

    store, whole = new_store(spark), state(spark, HISTORY[0])
    store.open_version(1)
    store.add(1, blocks.cut(whole.where("dataset_id = 'a'"), 32))
    with pytest.raises(StoreError):
        store.seal(1, protect.catalogue(whole), tracker.create_ledger(blocks.cut(whole, 32)))
    store = BlockStore(spark, store.path, 32, bucket_blocks=2)  # another driver goes on
    store.open_version(1)
    assert {r["dataset_id"] for r in store.missing(1, protect.catalogue(whole)).collect()} == {"b"}
    for _ in range(2):  # a repeated arrival changes nothing
        store.add(1, blocks.cut(whole, 32))
    store.seal(1, protect.catalogue(whole), tracker.create_ledger(blocks.cut(whole, 32)))
    assert rows(restore.read(store)) == rows(whole)


def test_early_commit_is_unsafe(spark):
    assert baselines.early_commit_loses(state(spark, HISTORY[0]), state(spark, HISTORY[1]), 32).count() == 1
