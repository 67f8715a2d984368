"""Exact dedup, sharding and packing against brute force; and their defined cases."""

import hashlib
import zlib
from collections import Counter, defaultdict

import public_tokenizers
import pytest

from blockdelta.llm import exact_dedup, packing, sharding

ROWS = [(1, "Abc"), (2, "aBC"), (3, None), (4, ""), (5, "É"), (6, "é"), (7, "abc"), (7, "abc"), (8, "x" * 70_000), (9, "X" * 70_000), (None, "abc"), (None, "lone"), *((100 + k, "copy") for k in range(40))]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, "note") for i, t in ROWS], "doc_id long, text string, kept string").repartition(5)


def lower(text):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")


@pytest.mark.parametrize("capacity", [None, 1])
def test_dedup(docs, capacity):
    groups = defaultdict(list)
    for i, t in ROWS:
        groups[lower(t)].append(i)
    got = exact_dedup.mark_duplicates(docs, capacity=capacity).collect()
    assert len(got) == len(ROWS)
    for r in got:
        key = lower(r["text"])
        best = max((i for i in groups[key] if i is not None), default=None)
        assert (r["keep_id"], r["group_size"], r["kept"]) == (best, len(groups[key]), r["doc_id"] == best)
        assert r["text_sha256"] == hashlib.sha256(key.encode()).hexdigest()


def test_dedup_empty_and_names(docs):
    assert exact_dedup.mark_duplicates(docs.limit(0)).count() == 0
    out = exact_dedup.mark_duplicates(docs, prefix="p_")
    assert {r["kept"] for r in out.collect()} == {"note"} and "p_kept" in out.columns


def test_directory_doubles():
    def counted(hashes):
        def measure(bits, within):
            out = {}
            for h, size in hashes.items():
                if within is None or any(h >> (64 - d) == p for p, d in within):
                    p = h >> (64 - bits)
                    out[p] = (out.get(p, (0, 0))[0] + size, out.get(p, (0, 0))[1] + 1)
            return out

        return measure

    top = lambda slot, bits=4: slot << (64 - bits)
    directory = exact_dedup.grow_directory(counted({top(0): 5, top(1): 5, top(8): 1, top(15): 1}), 4, 5)
    assert directory.depth == 4 and [s for s, _ in directory.buckets()][:2] == [0, 1]
    assert sum(w for _, w in directory.buckets()) == 1 << directory.depth
    assert exact_dedup.grow_directory(counted({}), 4, 5).depth == 0
    # Two hashes that part after 15 bits only split a bucket that deep; a single large one does not.
    deep = exact_dedup.grow_directory(counted({0: 9, top(1, 15): 9, top(3, 2): 50}), 2, 10)
    assert deep.depth == 15 and deep.local[0] == deep.local[1] == 15 and deep.local[-1] <= 2


def test_owners_compare_in_one_exchange_of_texts(docs):
    keyed = docs.selectExpr("doc_id AS id", "xxhash64(text) AS h", "text AS norm")
    held = keyed.withColumn("owner", keyed["h"].cast("int") % 2 + 1).repartitionById(3, "owner").groupBy("owner", "h", "norm").count()
    plan = held._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange shufflepartitionid") == 1 and "hashpartitioning" not in plan


def test_colliding_hashes_stay_apart(spark):
    keyed = spark.createDataFrame([(1, 7, "a"), (2, 7, "b"), (3, 7, "a"), (4, -9, "c")], "id long, h long, norm string")
    index, _ = exact_dedup.build_index(keyed, 1)
    assert sorted((r["h"], r["keep_id"], r["n"]) for r in index.collect()) == [(-9, 4, 1), (7, 2, 1), (7, 3, 2)]


def test_shards(spark, docs):
    many = spark.createDataFrame([(i, f"text {i} " * (i % 9)) for i in range(3000)] + [(10_000 + i, "the same") for i in range(1500)] + [(20_000, None)], "doc_id long, text string")
    got = sharding.assign_shards(many).collect()
    assert len(got) == 4501
    sizes, slots = Counter(), defaultdict(list)
    for r in got:
        sizes[r["shard"]] += r["size"]
        slots[r["shard"]].append(r["slot"])
    mean = sum(sizes.values()) / 16
    assert len(sizes) == 16 and max(sizes.values()) < 1.05 * mean and min(sizes.values()) > 0.95 * mean
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    null = next(r for r in got if r["doc_id"] == 20_000)
    assert null["size"] == 1 and null["text_crc32"] == 0
    odd = sharding.assign_shards(docs)
    assert odd.count() == len(ROWS)
    by = {r["doc_id"]: r for r in odd.collect()}
    assert by[5]["text_crc32"] == zlib.crc32("É".encode()) and by[5]["size"] == 3
    assert sharding.assign_shards(docs.limit(0)).count() == 0


def test_shards_written(spark, tmp_path):
    rows = [(k % 50, f"text {k % 7} " * (k % 9), k, str(k), "own") for k in range(400)] + [(None, None, 400, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, h long, v string, shard string")
    sharding.write_shards(df, str(tmp_path / "out"), shards=4)
    back = spark.read.parquet(str(tmp_path / "out"))
    assert set(back.columns) == set(df.columns) and back.select("shard").distinct().count() > 1
    assert sorted(map(repr, back.select("doc_id", "text", "h", "v").collect())) == sorted(map(repr, df.select("doc_id", "text", "h", "v").collect()))


def test_shards_of_one_repeated_row(spark):
    df = spark.createDataFrame([(1, "the same")] * 1600, "doc_id long, text string")
    sizes = Counter(r["shard"] for r in sharding.assign_shards(df).collect())
    assert len(sizes) == 16 and max(sizes.values()) <= 110


def test_multiset_is_the_closest():
    from itertools import combinations

    counts = {700: 2, 411: 1, 333: 3, 90: 2, 17: 1}
    items = [n for n, c in counts.items() for _ in range(c)]
    for capacity in (50, 100, 800, 1348, 2000):
        best = max(sum(c) for k in range(len(items) + 1) for c in combinations(items, k) if sum(c) <= capacity)
        used = packing.closest_multiset({n: c for n, c in counts.items() if n <= capacity}, capacity)
        assert sum(n * c for n, c in used.items()) == best and all(c <= counts[n] for n, c in used.items())


def test_fillings_use_everything():
    counts = {n: (n * 7) % 13 + 1 for n in range(1, 2048, 31)} | {2048: 5}
    fillings, used = packing.fill_windows(counts, 2048), Counter()
    for f in fillings:
        assert sum(n * c for n, c in f.lengths) <= 2048
        used.update({n: c * f.times for n, c in f.lengths})
    assert used == Counter(counts)
    assert packing.fill_windows({}, 2048) == []


def test_packing(spark):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    rows = [(1, None), (2, ""), (3, "hello <|endoftext|> world"), (4, "word " * 9000), (5, "é😀\n\n  x" * 50), *((10 + k, f"document number {k} " * (k % 40)) for k in range(200)), (7, "twice"), (7, "twice"), (8, "a" + " " * 1_000_000 + "\n" * 1_000_000), (9, "ab" * 500_000), (300, "!?" * 500_000), (301, "x" + "\u3000" * 5000 + "y")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = packing.pack(df, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, public_tokenizers.path("byte_bpe_50k.json")).collect()
    import numpy as np

    pieces, windows = defaultdict(list), defaultdict(list)
    for r in got:
        pieces[r["doc_id"]].append(r)
        windows[r["sequence_id"]].append((r["offset"], r["length"]))
    for doc, text in rows:
        ids = library.encode(text or "", add_special_tokens=False).ids + [1]
        copies = 2 if doc == 7 else 1
        own = sorted(pieces[doc], key=lambda r: r["start"])
        assert sum(r["length"] for r in own) == copies * len(ids)
        for r in own:
            part = np.array(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes()
            assert r["ids_crc32"] == zlib.crc32(part) and r["doc_tokens"] == len(ids)
    for places in windows.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 2048
    total = sum(r["length"] for r in got)
    assert len(windows) * 2048 - total < 2048 * 2
    assert packing.pack(df.limit(0), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, public_tokenizers.path("byte_bpe_50k.json")).count() == 0


def test_staged_tables_can_be_forgotten(spark, docs):
    from blockdelta.llm import common

    assert exact_dedup.mark_duplicates(docs).count() == len(ROWS)
    assert common.forget_staged(spark) > 0 and common.forget_staged(spark) == 0
