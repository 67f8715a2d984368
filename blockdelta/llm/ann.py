"""Approximate nearest neighbours by cosine: one navigable small-world graph with levels per shard, results merged.

Vectors are dealt into shards of bounded bytes by a hash of their direction; one task turns a shard into flat arrays: vectors, ids, and for each
level a fixed number of neighbours for each member. Levels thin out at random (by a hash, so a repeated task builds the same
graph), and nodes are ordered by their highest level, so the members of a level are the first ones. Levels are built from the top: nodes enter
in batches, each finds its candidates by walking what is there already, chooses neighbours by the usual rule that a new one must be nearer
to it than to those already chosen, and is linked back; a node with too many links chooses anew. Only the first nodes of a level
are compared with each other in full. Vectors of one direction are one node, with as many of their smallest ids as a
result can need: more would crowd each other out of the graph and never be returned. Graphs are written to the shared folder, one row each.

Queries are packed into blocks; every shard meets every block, a bounded number of blocks a task, behind one copy of its graph. A
walk enters at the top level and at the bottom level follows the best unvisited candidates with a beam, so the
nodes it scores are bounded by beam and links, not by the shard. Each shard gives its best with their exact cosine in
double precision on the original vectors, and the best of all shards are kept.

Defined cases: null, zero or non-finite vectors take no part; vectors must share one length (others fail loudly); fewer candidates
than asked for are all returned; equal scores go by the smaller id; an empty table gives no rows. Rows repeated under one id
with one direction are one candidate, under other directions candidates each; a query is not its own neighbour under any of
them, and of a query's several vectors the smallest one asks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import map_batches, staged

#: Vectors of a shard and its bytes (about), queries of a block, blocks of a visit, and links on upper levels (twice as many on the bottom one).
SHARD_ROWS, SHARD_BYTES, BLOCK_ROWS, VISIT_BLOCKS, LINKS = 4096, 32 << 20, 512, 64, 16
#: Candidates that a walk keeps, in a search and in building; nodes of a level that are compared in full, and nodes that enter at once.
BEAM, BUILD_BEAM, SEED, BATCH = 128, 48, 256, 512
#: Fills up the ids of a node; no id can be smaller.
NO_ID = np.iinfo(np.int64).min


def usable(vector: Column) -> Column:
    """Not null, without null or non-finite components, and not zero."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    return F.coalesce(vector.isNotNull() & ~bad & F.exists(vector, lambda x: x != 0), F.lit(False))


def _mixed(ids: np.ndarray) -> np.ndarray:
    """A random-looking number for each id, the same in any repeated task."""
    x = (ids.astype(np.uint64) + np.uint64(0x632BE59BD9B4E019)) * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def _rise(ids: np.ndarray) -> np.ndarray:
    """The highest level of each node: one in LINKS rises a level."""
    u = ((_mixed(ids) >> np.uint64(11)).astype(np.float64) + 0.5) / 2.0**53
    return np.floor(-np.log(u) / np.log(LINKS)).astype(int)


def _gathered(unit: np.ndarray, numbers: np.ndarray, to: np.ndarray) -> np.ndarray:
    """Products of each row of ``to`` with the vectors of its row of numbers."""
    return np.matmul(unit[numbers], to[:, :, None])[:, :, 0]


def climb(unit: np.ndarray, links: np.ndarray, queries: np.ndarray, at: np.ndarray, limit: int) -> np.ndarray:
    """Goes to the best neighbour below ``limit`` as long as that is better."""
    at, best, moving = at.copy(), np.einsum("ij,ij->i", unit[at], queries), np.arange(len(queries))
    while len(moving):
        around = links[at[moving]]
        sims = np.where((around >= 0) & (around < limit), _gathered(unit, around, queries[moving]), -np.inf)
        k = sims.argmax(1)
        top = sims[np.arange(len(k)), k]
        better = top > best[moving]
        moving, k, top, around = moving[better], k[better], top[better], around[better]
        at[moving], best[moving] = around[np.arange(len(k)), k], top
    return at


def walk(unit: np.ndarray, links: np.ndarray, queries: np.ndarray, at: np.ndarray, beam: int, limit: int) -> tuple[np.ndarray, np.ndarray, int]:
    """(numbers, products) of the ``beam`` best nodes found for each query (-1 for none), and how many nodes were scored."""
    n, beam = len(queries), min(beam, limit)
    seen = np.zeros((n, limit), bool)
    found = np.full((n, beam), -1, np.int64)
    score = np.full((n, beam), -np.inf, np.float32)
    opened = np.ones((n, beam), bool)
    found[:, 0], score[:, 0], opened[:, 0] = at, np.einsum("ij,ij->i", unit[at], queries), False
    seen[np.arange(n), at] = True
    active, scored = np.arange(n), n
    while len(active):
        waiting = np.where(opened[active], -np.inf, score[active])
        k = waiting.argmax(1)
        go = waiting[np.arange(len(k)), k] > -np.inf
        active, k = active[go], k[go]
        if not len(active):
            break
        opened[active, k] = True
        around = links[found[active, k]]
        new = (around >= 0) & ~seen[active[:, None], around]
        seen[active[:, None], np.where(around >= 0, around, found[active, k][:, None])] = True
        scored += int(new.sum())
        sims = np.where(new, _gathered(unit, around, queries[active]), -np.inf)
        all_found = np.concatenate([found[active], np.where(new, around, -1)], 1)
        all_score = np.concatenate([score[active], sims], 1).astype(np.float32)
        all_open = np.concatenate([opened[active], ~new], 1)
        keep = np.argpartition(-all_score, beam - 1, axis=1)[:, :beam]
        found[active], score[active], opened[active] = (np.take_along_axis(x, keep, 1) for x in (all_found, all_score, all_open))
    return found, score, scored


def choose(unit: np.ndarray, own: np.ndarray, candidates: np.ndarray, sims: np.ndarray, count: int) -> np.ndarray:
    """``count`` of each row of candidates (-1 for none): diverse ones first, then the nearest of the others."""
    order = np.argsort(-sims, axis=1, kind="stable")
    candidates, sims = np.take_along_axis(candidates, order, 1), np.take_along_axis(sims, order, 1)
    vectors = unit[candidates]
    among = np.matmul(vectors, vectors.transpose(0, 2, 1))
    there = candidates >= 0
    nearest = np.full(sims.shape, -np.inf, np.float32)  # to those already chosen
    chosen = np.zeros(sims.shape, bool)
    for k in range(candidates.shape[1]):
        take = there[:, k] & (sims[:, k] > nearest[:, k]) & (chosen.sum(1) < count)
        chosen[:, k] = take
        nearest = np.where(take[:, None], np.maximum(nearest, among[:, k]), nearest)
    rank = np.argsort(np.where(chosen, 0, np.where(there, 1, 2)), axis=1, kind="stable")[:, :count]
    out = np.full((len(own), count), -1, np.int64)
    out[:, : rank.shape[1]] = np.where(np.take_along_axis(there, rank, 1), np.take_along_axis(candidates, rank, 1), -1)
    return out


def link_back(unit: np.ndarray, links: np.ndarray, sources: np.ndarray, targets: np.ndarray) -> None:
    """Adds each new node (of ``sources``) to the links of the nodes it chose (its row of ``targets``); a full node chooses anew."""
    width = links.shape[1]
    src, dst = np.repeat(sources, targets.shape[1]), targets.ravel()
    src, dst = src[dst >= 0], dst[dst >= 0]
    order = np.argsort(dst, kind="stable")
    src, dst = src[order], dst[order]
    nodes, first, number = np.unique(dst, return_index=True, return_counts=True)
    for a in range(0, len(nodes), 2048):
        some = slice(a, a + 2048)
        own, n = nodes[some], number[some]
        extra = np.full((len(own), int(n.max())), -1, np.int64)
        place = np.arange(extra.shape[1])[None, :] < n[:, None]
        extra[place] = src[first[some][0] : first[some][-1] + n[-1]]
        all_links = np.concatenate([links[own], extra], 1)
        fits = (all_links >= 0).sum(1) <= width
        packed = np.take_along_axis(all_links, np.argsort(all_links < 0, axis=1, kind="stable"), 1)
        links[own[fits]] = packed[fits, :width]
        if not fits.all():
            full, candidates = own[~fits], packed[~fits]
            sims = np.where(candidates >= 0, _gathered(unit, candidates, unit[full]), -np.inf)
            links[full] = choose(unit, full, candidates, sims, width)


def build_level(unit: np.ndarray, size: int, width: int, above: list[np.ndarray]) -> np.ndarray:
    """Links of the first ``size`` nodes; ``above`` are the levels over this one, from the top."""
    links = np.full((size, width), -1, np.int64)
    seed = min(size, SEED)
    sims = unit[:seed] @ unit[:seed].T
    np.fill_diagonal(sims, -np.inf)
    near = np.argsort(-sims, axis=1, kind="stable")[:, : min(BUILD_BEAM, seed - 1)]
    if seed > 1:
        targets = choose(unit, np.arange(seed), near, np.take_along_axis(sims, near, 1), width // 2)
        links[:seed, : width // 2] = targets
        mutual = (links[np.maximum(targets, 0)] == np.arange(seed)[:, None, None]).any(2)
        link_back(unit, links, np.arange(seed), np.where(mutual, -1, targets))
    begin = seed
    while begin < size:
        end = min(size, begin + min(BATCH, begin))
        queries, at = unit[begin:end], np.zeros(end - begin, np.int64)
        for level in above:
            at = climb(unit, level, queries, at, begin)
        found, score, _ = walk(unit, links, queries, at, BUILD_BEAM, begin)
        mates = queries @ queries.T
        np.fill_diagonal(mates, -np.inf)
        nearest = np.argsort(-mates, axis=1)[:, : min(LINKS, end - begin - 1)]
        candidates = np.concatenate([found, nearest + begin], 1)
        sims = np.concatenate([np.where(found >= 0, score, -np.inf), np.take_along_axis(mates, nearest, 1)], 1)
        targets = choose(unit, np.arange(begin, end), candidates, sims, width // 2)
        links[begin:end, : width // 2] = targets
        # Batch mates that chose each other are linked already.
        mutual = (targets >= begin) & (links[np.maximum(targets, 0)] == np.arange(begin, end)[:, None, None]).any(2)
        link_back(unit, links, np.arange(begin, end), np.where(mutual, -1, targets))
        begin = end
    return links


def build_graph(ids: np.ndarray, vectors: np.ndarray) -> dict[str, bytes | int]:
    """A shard's graph as flat arrays, level by level from the top. ``ids`` has a row of ids (or NO_ID) for each vector."""
    rise = _rise(ids[:, 0])
    order = np.lexsort((ids[:, 0], _mixed(~ids[:, 0]), -rise))
    ids, vectors, rise = ids[order], vectors[order], rise[order]
    unit = (vectors / np.linalg.norm(vectors, axis=1, keepdims=True)).astype(np.float32)
    levels: list[np.ndarray] = []
    for level in range(int(rise[0]), -1, -1):
        levels.append(build_level(unit, int((rise >= level).sum()), 2 * LINKS if level == 0 else LINKS, levels))
    links = np.concatenate([level.astype("<i4").ravel() for level in levels])
    return {"width": vectors.shape[1], "ids": ids.astype("<i8").tobytes(), "vectors": vectors.astype("<f8").tobytes(), "sizes": np.array([len(level) for level in levels], "<i4").tobytes(), "links": links.tobytes()}


_ARRAYS = ("width", "ids", "vectors", "sizes", "links")
_GRAPH = "shard long, width long, ids binary, vectors binary, sizes binary, links binary"


class Graph:
    """A shard's graph, read back from its arrays."""

    def __init__(self, width: int, ids: bytes, vectors: bytes, sizes: bytes, links: bytes):
        self.vectors = np.frombuffer(vectors, "<f8").reshape(-1, width)
        self.ids = np.frombuffer(ids, "<i8").reshape(len(self.vectors), -1)
        self.norms = np.linalg.norm(self.vectors, axis=1)
        self.unit = (self.vectors / self.norms[:, None]).astype(np.float32)
        self.levels, flat, last = [], np.frombuffer(links, "<i4"), len(np.frombuffer(sizes, "<i4")) - 1
        for k, size in enumerate(np.frombuffer(sizes, "<i4")):
            width = 2 * LINKS if k == last else LINKS
            self.levels.append(flat[: size * width].reshape(size, width))
            flat = flat[size * width :]
        self.scored = 0

    def search(self, queries: np.ndarray, beam: int) -> np.ndarray:
        """Numbers of the ``beam`` best vectors found for each of the unit ``queries`` (-1 for none)."""
        at = np.zeros(len(queries), np.int64)
        for level in self.levels[:-1]:
            at = climb(self.unit, level, queries, at, len(self.unit))
        found, _, scored = walk(self.unit, self.levels[-1], queries, at, beam, len(self.unit))
        self.scored += scored
        return found

    def nearest(self, asked: np.ndarray, original: np.ndarray, k: int, beam: int) -> tuple[np.ndarray, np.ndarray]:
        """(ids, exact cosines) of the ``k`` best for each query, nearest first, without the query's own id; -inf fills up."""
        norms = np.linalg.norm(original, axis=1)
        found = self.search((original / norms[:, None]).astype(np.float32), beam)
        exact = np.where(found < 0, -np.inf, _gathered(self.vectors, found, original) / (self.norms[found] * norms[:, None]))
        nodes = np.lexsort((self.ids[found, 0], -exact), axis=1)[:, : k + 1]
        names = self.ids[np.take_along_axis(found, nodes, 1)].reshape(len(asked), -1)
        exact = np.repeat(np.take_along_axis(exact, nodes, 1), self.ids.shape[1], axis=1)
        exact = np.where((names == NO_ID) | (names == asked[:, None]), -np.inf, exact)
        order = np.lexsort((names, -exact), axis=1)[:, :k]
        return np.take_along_axis(names, order, 1), np.take_along_axis(exact, order, 1)


def _matrix(lists: pa.Array) -> np.ndarray:
    lengths = lists.value_lengths().to_numpy(zero_copy_only=False)
    if len(lengths) and (lengths != lengths[0]).any():
        raise ValueError("vectors of different lengths")
    return lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(lists), -1)


def _build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Graphs from rows (shard, ids, vector) sorted by shard; a shard is held until the next one begins."""
    held: dict[str, list] = {"shard": [], "ids": [], "vectors": []}

    def out() -> pa.RecordBatch:
        vectors = np.concatenate(held["vectors"])
        ids = np.full((len(vectors), max(map(len, held["ids"]))), NO_ID)
        for row, own in zip(ids, held["ids"]):
            row[: len(own)] = own
        graph = build_graph(ids, vectors)
        columns = [pa.array([held["shard"][0]], pa.int64()), *(pa.array([graph[k]], pa.int64() if k == "width" else pa.binary()) for k in _ARRAYS)]
        return pa.RecordBatch.from_arrays(columns, names=["shard", *_ARRAYS])

    for batch in batches:
        shard = batch.column(0).to_numpy()
        if not len(shard):
            continue
        ids, vectors = batch.column(1).to_pylist(), _matrix(batch.column(2))
        edges = [0, *(np.flatnonzero(shard[1:] != shard[:-1]) + 1), len(shard)]
        for a, b in zip(edges, edges[1:]):
            if held["shard"] and held["shard"][0] != shard[a]:
                yield out()
                held = {"shard": [], "ids": [], "vectors": []}
            held["shard"].append(int(shard[a]))
            held["ids"] += ids[a:b]
            held["vectors"].append(vectors[a:b])
    if held["shard"]:
        yield out()


def _direction(vector: Column) -> Column:
    """The vector over its length to 14 places: vectors whose cosines differ by rounding errors only have the same."""
    wide = F.transform(vector, lambda x: x.cast("double"))

    def once(value: Column, use) -> Column:
        """``use`` of a value that is bound first: inside a lambda function it would be computed anew for each component."""
        return F.transform(F.array(value), use)[0]

    def over(size: Column) -> Column:
        return F.transform(wide, lambda x: F.round(x / size, 14) + 0.0)

    def scaled(most: Column) -> Column:  # squares neither overflow nor vanish
        return once(most * F.sqrt(F.aggregate(wide, F.lit(0.0), lambda a, x: a + (x / most) * (x / most))), over)

    return once(F.array_max(F.transform(wide, F.abs)), scaled)


def build_index(vectors: DataFrame, k: int, shard_rows: int | None = None) -> tuple[DataFrame, int]:
    """Graphs of all rows of ``vectors`` (id, vector), in the shared folder, and their number, for searches of up to ``k``."""
    # The limit on vectors of one direction works before the exchange, so one vector of many rows moves only this often from each task.
    keyed = vectors.select("id", "vector", _direction(F.col("vector")).alias("direction"))
    copy = F.row_number().over(Window.partitionBy("direction").orderBy("id"))
    nodes = keyed.dropDuplicates(["direction", "id"]).withColumn("copy", copy).where(F.col("copy") <= k + 1)
    nodes = nodes.groupBy("direction").agg(F.sort_array(F.collect_list("id")).alias("ids"), F.min_by("vector", "id").alias("vector"))
    nodes = staged(nodes.select("ids", "vector", F.xxhash64(F.lit(4), "direction").alias("h")), "ann-nodes")
    total, width = nodes.agg(F.count(F.lit(1)), F.max(F.size("vector"))).first()
    shards = max(1, -(-total // (shard_rows or max(1, min(SHARD_ROWS, SHARD_BYTES // (8 * max(1, width or 1)))))))
    dealt = nodes.select(F.pmod("h", F.lit(shards)).cast("int").alias("shard"), "ids", "vector").repartitionById(shards, "shard")
    dealt = dealt.select(F.col("shard").cast("long").alias("shard"), "ids", "vector").sortWithinPartitions("shard", "ids")
    return staged(map_batches(dealt, _build, _GRAPH), "ann-graphs"), shards


def search(index: DataFrame, shards: int, queries: DataFrame, k: int = 5, beam: int = BEAM) -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` best of all shards for each of ``queries`` (id, vector), but the query itself."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, BLOCK_ROWS):
                piece = batch.slice(a, BLOCK_ROWS)
                vectors = _matrix(piece.column(1)).astype("<f8")
                yield pa.RecordBatch.from_arrays([pa.array([piece.column(0).to_numpy().astype("<i8").tobytes()], pa.binary()), pa.array([vectors.tobytes()], pa.binary())], names=["query_ids", "query_vectors"])

    blocks = max(1, -(-queries.count() // BLOCK_ROWS))
    visits = -(-blocks // VISIT_BLOCKS)
    packed = map_batches(queries.repartition(blocks), pack, "query_ids binary, query_vectors binary")
    packed = staged(packed.withColumn("visit", F.pmod(F.xxhash64("query_ids"), F.lit(visits))), "ann-queries")
    every_shard, every_visit = (F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))) for n in (shards, visits))
    none = [F.lit(None).cast("binary").alias(c) for c in ("query_ids", "query_vectors")]
    graphs = index.select("shard", every_visit.alias("visit"), F.lit(0).alias("turn"), *_ARRAYS, *none)
    empty = [F.lit(0).cast("long").alias("width"), *(F.lit(None).cast("binary").alias(c) for c in _ARRAYS[1:])]
    asking = packed.select(every_shard.alias("shard"), "visit", F.lit(1).alias("turn"), *empty, "query_ids", "query_vectors")
    # One copy of a graph comes before the blocks of its visit.
    task = (F.col("shard") * visits + F.col("visit")).cast("int")
    met = graphs.unionByName(asking).repartitionById(shards * visits, task).sortWithinPartitions("shard", "visit", "turn")

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph = None
        for batch in batches:
            for row in range(batch.num_rows):
                _, _, turn, *arrays, query_ids, query_vectors = (batch.column(c)[row].as_py() for c in range(batch.num_columns))
                if turn == 0:
                    graph = Graph(*arrays)
                    continue
                asked = np.frombuffer(query_ids, "<i8")
                names, best = graph.nearest(asked, np.frombuffer(query_vectors, "<f8").reshape(len(asked), -1), k, beam)
                good = best > -np.inf
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(asked, good.sum(1))), pa.array(names[good]), pa.array(best[good])], names=["query_id", "vec_id", "score"])

    hits = map_batches(met, visit, "query_id long, vec_id long, score double")
    place = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return hits.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def nearest(table: DataFrame, is_query: Column, k: int = 5, shard_rows: int | None = None, beam: int = BEAM, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """The ``k`` nearest rows of each query row of ``table``."""
    vectors = table.where(usable(F.col(vector_col)) & F.col(id_col).isNotNull())
    index, shards = build_index(vectors.select(F.col(id_col).alias("id"), F.col(vector_col).alias("vector")), k, shard_rows)
    queries = vectors.where(is_query).groupBy(F.col(id_col).alias("id")).agg(F.min(F.col(vector_col)).alias("vector"))
    return search(index, shards, queries, k, beam)
