"""Registering datasets: from a table to positioned cells, and the catalogue of their sizes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.encode import cell_hex

WIDTH = 8
#: Rows that are packed together before anything else moves.
RUN = 2048


def register(df: DataFrame, dataset_id: Column | str, order: list[str], value: Column, rank: Column) -> DataFrame:
    """cells (rank, dataset_id, pos, cell); positions number the rows of a dataset by ``order``, which must be unique in it."""
    dataset = F.lit(dataset_id) if isinstance(dataset_id, str) else dataset_id
    named = df.select(*order, rank.cast("int").alias("rank"), dataset.alias("dataset_id"), value.alias("cell"))
    pos = F.row_number().over(Window.partitionBy("rank", "dataset_id").orderBy(*order)).cast("bigint") - 1
    return named.select("rank", "dataset_id", pos.alias("pos"), "cell")


def register_dense(df: DataFrame, dataset_id: str, key: str, value: Column, n: int, ranks: int) -> DataFrame:
    """cells of a key 0..n-1 cut into ``ranks`` ranges; positions are arithmetic, nothing is shuffled."""
    rank = F.expr(f"{key} * {ranks} div {n}")
    first = F.expr(f"(({key} * {ranks} div {n}) * {n} + {ranks - 1}) div {ranks}")
    return df.select(rank.cast("int").alias("rank"), F.lit(dataset_id).alias("dataset_id"), (F.col(key) - first).alias("pos"), value.alias("cell"))


def register_stacked(df: DataFrame, columns: dict[str, Column], order: list[str], rank: Column, group: Column) -> DataFrame:
    """cells with one dataset for each column and group; rows are numbered once, whatever the number of columns."""
    pos = F.row_number().over(Window.partitionBy("rank", "grp").orderBy(*order)).cast("bigint") - 1
    named = df.select(*order, rank.cast("int").alias("rank"), group.cast("bigint").alias("grp"), *[v.alias(f"c_{k}") for k, v in columns.items()])
    numbered = named.select("rank", "grp", pos.alias("pos"), *[f"c_{k}" for k in columns])
    stack = ", ".join(f"{i}, '{k}', c_{k}" for i, k in enumerate(columns))
    return numbered.selectExpr("rank", "grp", "pos", f"stack({len(columns)}, {stack}) AS (col_no, col_name, cell)")


def register_rows(df: DataFrame, old: dict[str, Column], new: dict[str, Column], order: list[str], rank: Column, group: Column, by_rank: bool = False) -> DataFrame:
    """(rank, grp, begin, held): runs of up to RUN numbered rows of a group, each row with its cells in two versions (o_0.., n_0..).

    ``new`` names the columns that differ; the others keep the cells of ``old``. Only the columns of ``order`` are moved, of which
    ``old`` and ``new`` must be functions; runs are gathered where the rows were numbered.
    With ``by_rank`` rows are dealt by rank alone, so that plans with other groups find them in the same shuffle."""
    names = list(old)
    pos = F.row_number().over(Window.partitionBy("rank", "grp").orderBy(*order)).cast("bigint") - 1
    named = df.select(*order, rank.cast("int").alias("rank"))
    named = (named.repartition("rank") if by_rank else named).withColumn("grp", group.cast("bigint"))
    cells = [old[k].alias(f"o_{i}") for i, k in enumerate(names)] + [new[k].alias(f"n_{i}") for i, k in enumerate(names) if k in new]
    numbered = named.withColumn("pos", pos).select("rank", "grp", "pos", *cells)
    run = F.expr(f"pos div {RUN} * {RUN}").alias("begin")
    return numbered.groupBy("rank", "grp", run).agg(F.array_sort(F.collect_list(F.struct("pos", *numbered.columns[3:]))).alias("held"))


def group_starts(df: DataFrame, rank: Column, group: Column) -> DataFrame:
    """(rank, grp, n, before): rows of each group, and those of the groups before it on its rank."""
    counts = df.groupBy(rank.cast("int").alias("rank"), group.cast("bigint").alias("grp")).agg(F.count(F.lit(1)).alias("n"))
    return counts.withColumn("before", F.sum("n").over(Window.partitionBy("rank").orderBy("grp").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n"))


def _packed(fields: list[str]) -> Column:
    return F.unhex(F.array_join(F.transform("held", lambda x: F.concat(*[cell_hex(x[f]) for f in fields])), ""))


def lay_out(rows: DataFrame, names: list[str], starts: DataFrame, variants: dict[str, tuple[str, str]]) -> DataFrame:
    """runs (variant, rank, dataset_id, start, old, new) of packed cells, as ``separate`` (``many``) or ``serialise`` (``one``) place them.

    ``variants`` are exposures and layouts by name; whatever their number, cells are packed once by columns and once by rows at most.
    ``new`` is null where it cannot differ. ``starts`` has a row for each rank and group."""
    k, fields = len(names), rows.schema["held"].dataType.elementType.names
    old, new = [f"o_{i}" for i in range(k)], [f"n_{i}" if f"n_{i}" in fields else None for i in range(k)]
    by_row = {v for v, (expose, layout) in variants.items() if expose == "one" and layout == "row"}
    packed = []
    if len(by_row) < len(variants):
        packed += [F.struct(F.lit(i).alias("col_no"), F.lit(c).alias("col_name"), _packed([old[i]]).alias("old"), (_packed([new[i]]) if new[i] else F.lit(None).cast("binary")).alias("new")) for i, c in enumerate(names)]
    if by_row:
        packed.append(F.struct(F.lit(-1).alias("col_no"), F.lit("").alias("col_name"), _packed(old).alias("old"), _packed([n or o for n, o in zip(new, old)]).alias("new")))
    runs = rows.join(F.broadcast(starts), ["rank", "grp"], "left").select("rank", "grp", "begin", "n", "before", F.inline(F.array(*packed)))

    def place(v: str) -> Column:
        if variants[v][0] == "many":
            dataset, start = F.concat_ws("_", "col_name", F.col("grp").cast("string")), F.col("begin")
        else:
            dataset, start = F.lit("all"), k * (F.col("before") + F.col("begin")) if v in by_row else k * F.col("before") + F.col("col_no") * F.col("n") + F.col("begin")
        return F.struct(F.lit(v).alias("variant"), dataset.alias("dataset_id"), start.alias("start"))

    none = F.array().cast("array<struct<variant:string,dataset_id:string,start:bigint>>")
    rows_, columns_ = (F.array(*[place(v) for v in variants if (v in by_row) == own]) if any((v in by_row) == own for v in variants) else none for own in (True, False))
    return runs.select("rank", "old", "new", F.inline(F.when(F.col("col_no") < 0, rows_).otherwise(columns_))).where(F.col("start").isNotNull())


def serialise(stacked: DataFrame, layout: str = "column", order: tuple[str, ...] = ("grp", "col_no")) -> DataFrame:
    """All datasets of a rank in one buffer: side by side in ``order``, or with ``layout='row'`` interleaved row by row."""
    sizes = stacked.groupBy("rank", "grp", "col_no").agg(F.count(F.lit(1)).alias("n"))
    if layout == "row":
        per = stacked.groupBy("rank", "grp").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("col_no").alias("k"))
        start = F.sum("n").over(Window.partitionBy("rank").orderBy("grp").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
        begin = per.select("rank", "grp", "k", start.alias("start"))
        joined = stacked.join(begin, ["rank", "grp"])
        pos = F.col("start") + F.col("pos") * F.col("k") + F.col("col_no")
    else:
        start = F.sum("n").over(Window.partitionBy("rank").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
        begin = sizes.select("rank", "grp", "col_no", start.alias("start"))
        joined = stacked.join(begin, ["rank", "grp", "col_no"])
        pos = F.col("start") + F.col("pos")
    return joined.select("rank", F.lit("all").alias("dataset_id"), pos.alias("pos"), "cell")


def separate(stacked: DataFrame) -> DataFrame:
    """One dataset for each column and group."""
    return stacked.select("rank", F.concat_ws("_", "col_name", F.col("grp").cast("string")).alias("dataset_id"), "pos", "cell")


def catalogue(cells: DataFrame) -> DataFrame:
    """Size of each dataset on each rank."""
    return cells.groupBy("rank", "dataset_id").agg((F.count(F.lit(1)) * WIDTH).alias("size_bytes"))


def resize(before: DataFrame, after: DataFrame, b: int) -> DataFrame:
    """What a change of sizes means: bytes and blocks before and after, and the blocks that only now exist."""
    old = before.select("rank", "dataset_id", F.col("size_bytes").alias("old_bytes"))
    both = old.join(after.select("rank", "dataset_id", F.col("size_bytes").alias("new_bytes")), ["rank", "dataset_id"], "full_outer").fillna(0, ["old_bytes", "new_bytes"])
    blocks = {c: F.expr(f"({c}_bytes + {b - 1}) div {b}") for c in ("old", "new")}
    return both.select("rank", "dataset_id", "old_bytes", "new_bytes", blocks["old"].alias("old_blocks"), blocks["new"].alias("new_blocks"), F.greatest(F.lit(0), blocks["new"] - blocks["old"]).alias("added_blocks"))


def check_positions(cells: DataFrame) -> None:
    """Raises if two cells share a position."""
    twice = cells.groupBy("rank", "dataset_id", "pos").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).collect()
    if twice:
        raise ValueError(f"two cells at rank {twice[0]['rank']}, dataset {twice[0]['dataset_id']}, position {twice[0]['pos']}")
