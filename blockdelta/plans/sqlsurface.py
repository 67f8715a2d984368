"""The engine's steps in SQL text: views ``blocks``, ``ledger``, ``states`` and ``regions``, and a SQL function ``block_of(pos, b)``."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..functions.digests import digest
from ..operators import blocks as cutting


def register(cells: DataFrame, ledger: DataFrame, b: int, algo: str = "md5") -> None:
    """Makes the views for one state against one ledger."""
    spark = cells.sparkSession
    cutting.check_size(b)
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION block_of(pos BIGINT, b INT) RETURNS BIGINT RETURN pos * 8 DIV b")
    cells.createOrReplaceTempView("cells")
    ledger.createOrReplaceTempView("ledger")
    spark.sql(f"""
        SELECT rank, dataset_id, block_of(pos, {b}) AS block_no, count(*) * 8 AS block_len,
               unhex(listagg(lpad(hex(cell), 16, '0')) WITHIN GROUP (ORDER BY pos)) AS payload
        FROM cells GROUP BY ALL""").createOrReplaceTempView("blocks")
    spark.table("blocks").select(*cutting.KEYS, "block_len", digest(spark.table("blocks")["payload"], algo).alias("digest")).createOrReplaceTempView("hashed")
    spark.sql("""
        SELECT rank, dataset_id, block_no, coalesce(n.block_len, o.block_len) AS block_len,
               CASE WHEN n.block_len IS NULL THEN 'retired'
                    WHEN o.block_len IS NULL OR o.block_len <> n.block_len THEN 'invalid'
                    WHEN n.digest <=> o.digest THEN 'clean' ELSE 'dirty' END AS status
        FROM hashed n FULL OUTER JOIN ledger o USING (rank, dataset_id, block_no)""").createOrReplaceTempView("states")
    spark.sql(f"""
        WITH numbered AS (
          SELECT *, block_no - row_number() OVER (PARTITION BY rank, dataset_id ORDER BY block_no) AS island
          FROM states WHERE status IN ('dirty', 'invalid'))
        SELECT rank, dataset_id, CAST(min(block_no) * {b} AS BIGINT) AS start_byte, sum(block_len) AS n_bytes, count(*) AS n_blocks,
               count_if(status = 'invalid') AS n_invalid
        FROM numbered GROUP BY rank, dataset_id, island""").createOrReplaceTempView("regions")


def regions(cells: DataFrame, ledger: DataFrame, b: int, algo: str = "md5") -> DataFrame:
    register(cells, ledger, b, algo)
    return cells.sparkSession.sql("SELECT * FROM regions")
