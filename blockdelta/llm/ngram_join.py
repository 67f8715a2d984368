"""Exact similarity join of texts on word shingles: Jaccard similarity at or above a threshold, by prefix filtering.

* Texts with one set form a class and take part once, so copies cost one row each.
* Shingles are ordered rare first, by counts from a table of fixed size that is filled from all texts (a shingle's
  count may include others that share its slot; any common order keeps the filter exact), then by hash.
* A similar pair shares one of the first n - ceil(t n) + 1 shingles of each. Rows of these prefixes meet by shingle,
  sorted by set size; length and positional filters drop pairs before they are formed.
* Components come first. Few rows at a shingle: all their pairs are candidates. Many rows: at first each is held against one of them, the
  class that most crowded shingles have. Candidates are verified in steps, the best one of each class first, and those within a
  component wait. At last the rows of crowded shingles meet again with their components known, and all pairs across components
  become candidates. No link that joins two components is lost.
* Links come from components: every link lies within one, so the classes of each are dealt into blocks, and in each pair of blocks
  all intersections are counted exactly. This is quadratic in the size of a component, as the number of its links can be.
* On the way to components each candidate pair is verified once. A suffix filter over the whole sets comes first: every class keeps how many of its shingles fall
  into each of equal ranges of hashes, about four a range, and the smaller counts of two classes bound their intersection. Then the
  sets of the texts concerned are computed anew and intersected exactly.

Defined cases: null or wordless texts have no shingles and link with nothing; a text of fewer than five words is one
shingle; an empty table gives no rows; rows repeated under one id are nodes each, named by that id; null ids are never the smallest.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import look_up, map_batches, staged
from .components import connected, extended
from .shingles import shingle_sets

#: Slots of the count table and parts in which it is summed.
SLOT_BITS, PARTS = 18, 16
#: Rows at a shingle up to which all pairs are formed at once.
FEW = 8
#: Slots of the filter that tells which texts are hashed again for verification.
FILTER_BITS = 20
#: Classes and shingles of a block whose classes are held against each other at once, and cells of a matrix of classes by shingles.
BLOCK_CLASSES, BLOCK_SHINGLES, CELLS = 512, 500_000, 1 << 23
#: Bits of the largest number of ranges whose counts bound an intersection, and bits of a shingle by which prefixes meet.
RANGE_BITS, MEET_BITS = 12, 48


class Threshold:
    """A Jaccard threshold as an exact fraction."""

    def __init__(self, t: Fraction):
        self.num, self.den = t.numerator, t.denominator

    def prefix(self, n: int) -> int:
        return n - -(-n * self.num // self.den) + 1

    def sizes_fit(self, small, large):
        return small * self.den >= large * self.num

    def overlap(self, a, b):
        """The least intersection of similar sets with these sizes."""
        return -(-(a + b) * self.num // (self.num + self.den))


def slot_counts(docs: DataFrame, text_col: str) -> np.ndarray:
    """How often shingles of each slot occur, over all texts: a table of fixed size, summed part by part on the executors."""
    width = (1 << SLOT_BITS) // PARTS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << SLOT_BITS, np.int64)
        for batch in batches:
            for part in range(0, batch.num_rows, 512):
                sets = list(shingle_sets(batch.column(0).slice(part, 512).to_pylist()))
                if sets:
                    total += np.bincount((np.concatenate(sets) >> np.uint64(64 - SLOT_BITS)).astype(np.int64), minlength=1 << SLOT_BITS)
        if total.any():
            rows = [total[k * width : (k + 1) * width].tobytes() for k in range(PARTS)]
            yield pa.RecordBatch.from_arrays([pa.array(range(PARTS), pa.int32()), pa.array(rows, pa.binary())], names=["part", "counts"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for part, counts in zip(batch.column(0).to_pylist(), batch.column(1)):
                sums[part] = sums.get(part, 0) + np.frombuffer(counts.as_py(), np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([s.tobytes() for s in sums.values()], pa.binary())], names=["part", "counts"])

    counted = map_batches(docs.select(text_col), count, "part int, counts binary").repartition(PARTS, "part")
    summed = map_batches(counted, add, "part int, counts binary")
    table = np.zeros(1 << SLOT_BITS, np.int64)
    for r in summed.collect():  # PARTS rows
        table[r["part"] * width : (r["part"] + 1) * width] = np.frombuffer(r["counts"], np.int64)
    return table


def range_counts(s: np.ndarray) -> bytes | None:
    """How many of a sorted set's hashes fall into each of 2**k equal ranges, a byte each; null for an empty set or if a count is too large."""
    if not len(s):
        return None
    bits = min(RANGE_BITS, max(0, (len(s) // 4).bit_length()))
    counts = np.bincount((s >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(s), np.int64), minlength=1 << bits)
    return counts.astype(np.uint8).tobytes() if counts.max() < 256 else None


def intersection_bound(x: bytes, y: bytes) -> tuple[int, int, int]:
    """(most shingles in common, size, size) of two sets by their counts; the finer counts are summed to the coarser ranges."""
    x, y = (np.frombuffer(v, np.uint8).astype(np.int64) for v in (x, y))
    k = min(len(x), len(y))
    return int(np.minimum(x.reshape(k, -1).sum(1), y.reshape(k, -1).sum(1)).sum()), int(x.sum()), int(y.sum())


def prefixes(docs: DataFrame, counts: np.ndarray, t: Threshold, id_col: str, text_col: str) -> DataFrame:
    """id, n, sig (of the whole set; null for an empty one), counts by range, and the prefix in rare-first order, per row."""
    shared = docs.sparkSession.sparkContext.broadcast(counts.astype(np.int64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rank = shared.value
        for batch in batches:
            for part in range(0, batch.num_rows, 512):
                piece, n, sig, ranges, first = batch.slice(part, 512), [], [], [], []
                for s in shingle_sets(piece.column(1).to_pylist()):
                    n.append(len(s))
                    sig.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
                    ranges.append(range_counts(s))
                    order = np.lexsort((s, rank[(s >> np.uint64(64 - SLOT_BITS)).astype(np.int64)]))
                    first.append((s[order[: t.prefix(len(s))]] >> np.uint64(64 - MEET_BITS)).view(np.int64) if len(s) else np.zeros(0, np.int64))
                offsets = np.cumsum([0, *map(len, first)])
                lists = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(np.concatenate(first)))
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(n, pa.int64()), pa.array(sig, pa.binary()), pa.array(ranges, pa.binary()), lists], names=["id", "n", "sig", "ranges", "prefix"])

    return map_batches(docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")), run, "id long, n long, sig binary, ranges binary, prefix array<long>")


def _pairs_near(token, cid, n, pos, most: int, t: Threshold) -> list[tuple[np.ndarray, np.ndarray]]:
    """Pairs of rows of one token up to ``most`` places apart that pass the length and positional filters."""
    out = []
    for d in range(1, most + 1):
        if len(token) <= d:
            break
        same = token[:-d] == token[d:]
        if not same.any():
            break
        i = np.flatnonzero(same)
        j = i + d
        ok = t.sizes_fit(n[i], n[j]) & (np.minimum(n[i] - pos[i], n[j] - pos[j]) >= t.overlap(n[i], n[j]))
        out.append((cid[i[ok]], cid[j[ok]]))
    return out


_MEET = "a long, b long, token long, n long, pos long"


def _batch(a, b, token=None, n=None, pos=None) -> pa.RecordBatch:
    blank = pa.nulls(len(a), pa.int64())
    return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) if x is not None else blank for x in (a, b, token, n, pos)], names=["a", "b", "token", "n", "pos"])


def _whole_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[list[np.ndarray]]:
    """Columns of sorted batches, cut where the first column changes, so that no run of equal values is parted."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        columns = [c.to_numpy(zero_copy_only=False) for c in batch.columns]
        new = np.flatnonzero(columns[0] != columns[0][-1])
        last = held[-1][0][-1] if held else None
        if len(new) == 0 and (last is None or last == columns[0][-1]):
            held.append(columns)
            continue
        cut = new[-1] + 1 if len(new) else 0
        held.append([c[:cut] for c in columns])
        yield [np.concatenate(c) for c in zip(*held)]
        held = [[c[cut:] for c in columns]]
    if held:
        yield [np.concatenate(c) for c in zip(*held)]


def _first_meeting(t: Threshold):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for token, cid, n, pos in _whole_runs(batches):
            edge = np.flatnonzero(np.concatenate([[True], token[1:] != token[:-1]]))
            length = np.repeat(np.diff(np.append(edge, len(token))), np.diff(np.append(edge, len(token))))
            few, many = (length > 1) & (length <= FEW), length > FEW
            pairs = _pairs_near(*(x[few] for x in (token, cid, n, pos)), FEW, t)
            if pairs:
                both = np.sort(np.stack([np.concatenate([p[k] for p in pairs]) for k in (0, 1)], 1), axis=1)
                both, times = np.unique(both, axis=0, return_counts=True)
                if len(both):
                    yield _batch(both[:, 0], both[:, 1], n=times)
            if many.any():
                yield _batch(cid[many], np.full(many.sum(), -1), token[many], n[many], pos[many])

    return run


def _second_meeting(t: Threshold):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for token, cid, n, pos, comp in _whole_runs(batches):
            edge = np.append(np.flatnonzero(np.concatenate([[True], token[1:] != token[:-1]])), len(token))
            for a, b in zip(edge, edge[1:]):
                if (comp[a:b] == comp[a]).all():
                    continue
                c, size, place, part = cid[a:b], n[a:b], pos[a:b], comp[a:b]
                names, where, count = np.unique(part, return_inverse=True, return_counts=True)
                # Members of the largest component need no turn of their own: every other row is held against all rows.
                turn = np.flatnonzero(where != count.argmax())
                done = np.zeros(len(c), bool)
                for i in turn:
                    done[i] = True
                    small, large = np.minimum(size[i], size), np.maximum(size[i], size)
                    ok = ~done & (part != part[i]) & t.sizes_fit(small, large) & (np.minimum(size[i] - place[i], size - place) >= t.overlap(size[i], size))
                    if ok.any():
                        other = c[ok]
                        yield _batch(np.minimum(other, c[i]), np.maximum(other, c[i]))

    return run


def _may_match(t: Threshold):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(6).to_pylist(), batch.column(7).to_pylist()):
                if x is not None and y is not None:
                    common, m, n = intersection_bound(x, y)
                good.append(x is None or y is None or common >= t.overlap(m, n))
            yield pa.RecordBatch.from_arrays([batch.column(k).filter(pa.array(good, pa.bool_())) for k in range(6)], names=batch.schema.names[:6])

    return run


def _verify(t: Threshold):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = []
            for x, y in zip(batch.column(2), batch.column(3)):
                x, y = (np.asarray(v.values).view(np.uint64) for v in (x, y))
                good.append(len(np.intersect1d(x, y, assume_unique=True)) >= t.overlap(len(x), len(y)))
            keep = pa.array(good, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(k).filter(keep) for k in (0, 1)], names=["a", "b"])

    return run


def sets_of(ids: DataFrame, docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(id, sig, items): the sets, computed anew, of the rows with these ids and of some others."""
    mask = np.zeros(1 << FILTER_BITS, bool)
    mask[ids.select(F.pmod(F.xxhash64("id"), F.lit(1 << FILTER_BITS)).alias("s")).distinct().toArrow().column(0).to_numpy()] = True  # at most 2**FILTER_BITS numbers
    shared = docs.sparkSession.sparkContext.broadcast(np.packbits(mask))

    def again(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        wanted_slots = np.unpackbits(shared.value).astype(bool)
        for batch in batches:
            batch = batch.filter(pa.array(wanted_slots[batch.column(0).to_numpy()]))
            if not batch.num_rows:
                continue
            for part in range(0, batch.num_rows, 128):
                piece = batch.slice(part, 128)
                sets = list(shingle_sets(piece.column(1).to_pylist()))
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *map(len, sets)]), pa.int32()), pa.array(np.concatenate(sets).view(np.int64)))
                sig = pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary())
                yield pa.RecordBatch.from_arrays([piece.column(2), sig, lists], names=["id", "sig", "items"])

    own = F.col(id_col).cast("long")
    hashed = docs.select(F.pmod(F.xxhash64(own), F.lit(1 << FILTER_BITS)).alias("slot"), F.col(text_col).alias("text"), own.alias("id")).where(F.col("id").isNotNull())
    return map_batches(hashed, again, "id long, sig binary, items array<long>")


def verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame, t: Threshold, id_col: str, text_col: str) -> DataFrame:
    """The pairs (a, b) of classes that are similar. Sets are computed again, for one text of each class in a pair."""
    ends = classes.select("cid", "min_id", "sig", "ranges")
    named = pairs
    for end in "ab":
        named = named.join(ends.select(*[F.col(c).alias(f"{c}_{end}") for c in ends.columns]), F.col(end) == F.col(f"cid_{end}"))
    named = named.select("a", "b", "min_id_a", "sig_a", "min_id_b", "sig_b", "ranges_a", "ranges_b")
    wanted = staged(map_batches(named, _may_match(t), "a long, b long, min_id_a long, sig_a binary, min_id_b long, sig_b binary"), "join-wanted")
    # The sets are the large side, so they are exchanged by id once and serve both ends of the pairs.
    sets = sets_of(wanted.select(F.explode(F.array("min_id_a", "min_id_b")).alias("id")), docs, id_col, text_col).hint("merge")
    left = wanted.join(sets.select(F.col("id").alias("id_a"), F.col("sig").alias("s_a"), F.col("items").alias("x")), (F.col("min_id_a") == F.col("id_a")) & (F.col("sig_a") == F.col("s_a")))
    left = left.select("a", "b", "min_id_b", "sig_b", "x")
    both = left.join(sets.select(F.col("id").alias("id_b"), F.col("sig").alias("s_b"), F.col("items").alias("y")), (F.col("min_id_b") == F.col("id_b")) & (F.col("sig_b") == F.col("s_b"))).select("a", "b", "x", "y")
    return map_batches(both, _verify(t), "a long, b long")


def _stars(crowded: DataFrame, centre: Column, t: Threshold) -> DataFrame:
    """Candidate pairs (a, b): the rows of a crowded shingle against the one of them with the largest ``centre``, unless of its component.

    ``crowded`` has token, cid, n and component.
    """
    pivot = crowded.groupBy("token").agg(F.max(F.struct(centre.alias("rank"), "cid", "n", "component")).alias("p"))
    pivot = pivot.select(F.col("token").alias("at"), F.col("p.cid").alias("c2"), F.col("p.n").alias("n2"), F.col("p.component").alias("k2"))
    met = crowded.join(pivot, F.col("token") == F.col("at")).where("component <> k2")
    small, large = F.least("n", "n2"), F.greatest("n", "n2")
    return met.where(small * t.den >= large * t.num).select(F.least("cid", "c2").alias("a"), F.greatest("cid", "c2").alias("b")).distinct()


def _with_components(rows: DataFrame, parts: DataFrame) -> DataFrame:
    """``rows`` with the component of their class ``cid``; its own where it has no link."""
    known = parts.select(F.col("node").alias("member"), F.col("component").alias("part"))
    return rows.join(known, F.col("cid") == F.col("member"), "left").withColumn("component", F.coalesce("part", "cid")).drop("member", "part")


def _across(pairs: DataFrame, parts: DataFrame) -> DataFrame:
    """The pairs whose classes are not connected yet."""
    out = pairs
    for end in "ab":
        out = out.join(parts.select(F.col("node").alias(f"node_{end}"), F.col("component").alias(f"part_{end}")), F.col(end) == F.col(f"node_{end}"), "left")
    return out.where(F.coalesce("part_a", "a") != F.coalesce("part_b", "b")).select("a", "b")


def join_classes(docs: DataFrame, threshold: Fraction, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows (id, n, sig), classes (cid, sig, min_id, copies, ..) and the component (node, component) of each linked class."""
    t = Threshold(threshold)
    rows = staged(prefixes(docs, slot_counts(docs, text_col), t, id_col, text_col), "join-prefixes")
    named = rows.where(F.col("sig").isNotNull()).groupBy("sig").agg(F.min("id").alias("min_id"), F.count(F.lit(1)).alias("copies"), F.first("n").alias("n"), F.first("ranges").alias("ranges"), F.first("prefix").alias("prefix"))
    classes = staged(named.withColumn("cid", F.monotonically_increasing_id()), "join-classes")
    posted = classes.select("cid", "n", F.posexplode("prefix").alias("pos", "token")).select("token", "cid", "n", F.col("pos").cast("long").alias("pos"))
    ways = int(posted.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    met = posted.repartition(ways, "token").sortWithinPartitions("token", "n", "cid")
    met = staged(map_batches(met, _first_meeting(t), _MEET), "join-meetings")
    pairs = staged(met.where("b >= 0").groupBy("a", "b").agg(F.sum("n").alias("times")), "join-pairs")
    crowded = met.where("b < 0").select("token", F.col("a").alias("cid"), "n", "pos")
    some_crowded = crowded.limit(1).count() > 0
    best = pairs.groupBy("a").agg(F.max(F.struct("times", "b")).alias("m")).select("a", F.col("m.b").alias("b"))
    best = best.union(pairs.groupBy("b").agg(F.max(F.struct("times", "a")).alias("m")).select(F.col("m.a").alias("a"), "b"))
    if some_crowded:
        spread = crowded.groupBy("cid").agg(F.count(F.lit(1)).alias("spread"))
        crowded = staged(crowded.join(spread, "cid"), "join-crowded")
        best = best.union(_stars(crowded.withColumn("component", F.col("cid")), F.col("spread"), t))
    done = staged(best.distinct(), "join-pairs")
    links = staged(verified(done, docs, classes, t, id_col, text_col), "join-links")
    parts = staged(connected(links), "components")
    if some_crowded:
        # What missed the main class may well be similar to others around it: try one of these at each shingle, another one each time.
        placed = staged(_with_components(crowded, parts), "join-crowded")
        main = placed.groupBy("token").agg(F.max(F.struct("spread", "cid", "component")).alias("p")).select(F.col("token").alias("main_at"), F.col("p.component").alias("main"))
        centre = F.when(F.col("component") == F.col("main"), F.xxhash64("token", "cid"))
        more = _stars(placed.join(main, F.col("token") == F.col("main_at")), centre, t)
        more = staged(more.join(done, ["a", "b"], "left_anti"), "join-pairs")
        done = done.union(more)
        parts = extended(parts, staged(verified(more, docs, classes, t, id_col, text_col), "join-links"))
    more = _across(pairs.join(done, ["a", "b"], "left_anti"), parts)
    if some_crowded:
        again = _with_components(crowded.select("token", "cid", "n", "pos"), parts).select("token", "cid", "n", "pos", "component")
        again = again.repartition(ways, "token").sortWithinPartitions("token", "n", "cid")
        more = more.union(map_batches(again, _second_meeting(t), _MEET).select("a", "b").join(done, ["a", "b"], "left_anti"))
    more = staged(more.distinct(), "join-pairs")
    if more.limit(1).count():
        parts = extended(parts, staged(verified(more, docs, classes, t, id_col, text_col), "join-links"))
    return rows.select("id", "n", "sig"), classes.select("cid", "sig", "min_id", "copies", "n"), parts


def _common(owner: np.ndarray, items: np.ndarray, k: int) -> np.ndarray:
    """Above the diagonal, the sizes of the intersections of ``k`` sets, given as all their items with the set of each, sets in order."""
    order = np.argsort(items, kind="stable")
    owner, items = owner[order], items[order]
    edge = np.flatnonzero(np.concatenate([[True], items[1:] != items[:-1]])) if len(items) else np.zeros(0, np.int64)
    length = np.diff(np.append(edge, len(items)))
    common, held = np.zeros(k * k, np.int64), np.repeat(length, length)
    few = (held > 1) & (held <= FEW)
    item, own = items[few], owner[few]
    for d in range(1, FEW):
        same = np.flatnonzero(item[:-d] == item[d:])
        if not len(same):
            break
        common += np.bincount(own[same] * k + own[same + d], minlength=k * k)
    common = common.reshape(k, k)
    many = held > FEW
    own, column = owner[many], np.repeat(np.arange((length > FEW).sum()), length[length > FEW])
    width = max(1, CELLS // max(1, k))
    for first in range(0, int(column[-1]) + 1 if len(column) else 0, width):
        lo, hi = np.searchsorted(column, [first, first + width])
        matrix = np.zeros((k, int(column[hi - 1]) + 1 - first), np.float32)
        matrix[own[lo:hi], column[lo:hi] - first] = 1
        common += (matrix @ matrix.T).astype(np.int64)
    return common


def _similar(table: pa.Table, t: Threshold) -> tuple[np.ndarray, np.ndarray]:
    """(cid, matrix): the classes of a pair of blocks, and above the diagonal which are similar; within one block only if it stands alone."""
    cid, at = np.unique(table.column("cid").to_numpy(), return_index=True)  # rows repeated under one id bring a class twice
    block, sets = table.column("block").to_numpy()[at], table.column("items").take(pa.array(at)).combine_chunks()
    n = sets.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    common = _common(np.repeat(np.arange(len(cid)), n), sets.flatten().to_numpy(zero_copy_only=False), len(cid))
    similar = np.triu(common >= t.overlap(n[:, None], n[None, :]), 1)
    if block.min() != block.max():
        similar &= block[:, None] != block[None, :]
    elif table.column("i")[0].as_py() != table.column("j")[0].as_py():
        similar[:] = False  # the other block has no classes
    return cid, similar


def _links_of_blocks(t: Threshold):
    def run(table: pa.Table) -> pa.Table:
        cid, similar = _similar(table, t)
        a, b = np.nonzero(similar)
        return pa.table({"a": pa.array(cid[a], pa.int64()), "b": pa.array(cid[b], pa.int64())})

    return run


def _degrees_of_blocks(t: Threshold):
    def run(table: pa.Table) -> pa.Table:
        cid, similar = _similar(table, t)
        degree = similar.sum(0) + similar.sum(1)
        some = degree > 0
        return pa.table({"cid": pa.array(cid[some], pa.int64()), "n_links": pa.array(degree[some], pa.int64())})

    return run


def _block_pairs(docs: DataFrame, classes: DataFrame, parts: DataFrame, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """Components of two classes as pairs (a, b), and the sets of the larger ones once for each pair (i, j) of blocks they have part in."""
    known = parts.select(F.col("node").alias("cid"), "component")
    sizes = known.join(classes.select("cid", "n"), "cid").groupBy("component").agg(F.count(F.lit(1)).alias("k"), F.sum("n").alias("total"), F.min("cid").alias("a"), F.max("cid").alias("b"))
    sizes = staged(sizes, "join-sizes")
    alone = sizes.where("k = 2").select("a", "b")
    ways = F.greatest(F.ceil(F.col("k") / BLOCK_CLASSES), F.ceil(F.col("total") / BLOCK_SHINGLES)).cast("int")
    members = known.join(sizes.where("k > 2").select("component", ways.alias("ways")), "component").join(classes.select("cid", "min_id", "sig"), "cid")
    members = staged(members.withColumn("block", F.pmod(F.xxhash64("cid"), F.col("ways")).cast("int")), "join-members")
    sets = sets_of(members.select(F.col("min_id").alias("id")), docs, id_col, text_col).withColumnRenamed("sig", "own_sig")
    full = members.join(sets, (F.col("min_id") == F.col("id")) & (F.col("sig") == F.col("own_sig"))).select("component", "ways", "block", "cid", "items")
    dealt = full.select("component", "block", "cid", "items", F.explode(F.sequence(F.lit(0), F.col("ways") - 1)).alias("other"))
    dealt = dealt.select("component", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "cid", "items")
    return alone, dealt


def all_links(docs: DataFrame, classes: DataFrame, parts: DataFrame, threshold: Fraction, id_col: str, text_col: str) -> DataFrame:
    """Every pair (a, b) of similar classes, a below b, once."""
    alone, dealt = _block_pairs(docs, classes, parts, id_col, text_col)
    return alone.union(dealt.groupBy("component", "i", "j").applyInArrow(_links_of_blocks(Threshold(threshold)), "a long, b long"))


def link_counts(docs: DataFrame, classes: DataFrame, parts: DataFrame, threshold: Fraction, id_col: str, text_col: str) -> DataFrame:
    """(end, n_links): how many other classes are similar to each linked one. Blocks give sums a class, so no pair leaves its task."""
    alone, dealt = _block_pairs(docs, classes, parts, id_col, text_col)
    counted = dealt.groupBy("component", "i", "j").applyInArrow(_degrees_of_blocks(Threshold(threshold)), "cid long, n_links long")
    ends = alone.select(F.explode(F.array("a", "b")).alias("cid"), F.lit(1).cast("long").alias("n_links"))
    return counted.union(ends).groupBy(F.col("cid").alias("end")).agg(F.sum("n_links").alias("n_links"))


def near_duplicates(docs: DataFrame, threshold: Fraction = Fraction(4, 5), id_col: str = "doc_id", text_col: str = "text", links: bool = True) -> DataFrame:
    """Per row: id, n_shingles, component_id (the smallest id reachable by links), copies (rows with the very same set) and n_links
    (other sets that are similar); without ``links`` the last column is left out, and with it the work on links within components."""
    rows, classes, parts = join_classes(docs, threshold, id_col, text_col)
    member = classes.join(parts.select(F.col("node").alias("cid"), "component"), "cid", "left").withColumn("component", F.coalesce("component", "cid"))
    if links:
        degree = link_counts(docs, classes, parts, threshold, id_col, text_col)
        member = member.join(staged(degree, "join-degrees"), F.col("cid") == F.col("end"), "left")
    least = member.groupBy("component").agg(F.min("min_id").alias("component_id"))
    more = ["n_links"] if links else []
    names = staged(member.join(least, "component").select("sig", "copies", "component_id", *more), "join-components")
    found = look_up(rows, names, "sig", "copies", F.xxhash64("id", "n"))
    counts = [F.coalesce(c, F.lit(d)).cast("long").alias(c) for c, d in [("copies", 1), *((c, 0) for c in more)]]
    return found.select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component_id", "id").alias("component_id"), *counts)
