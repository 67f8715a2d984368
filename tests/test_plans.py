"""Physical plans: pruned scans, no single task for all rows, no Python on the engine's own path, and independence of the text operators."""

import contextlib
import io
import pathlib
import re
import subprocess
import sys

import pytest

from blockdelta import catalogue

ROOT = pathlib.Path(__file__).resolve().parents[1]


def plan(df):
    out = io.StringIO()
    with contextlib.redirect_stdout(out):
        df.explain("formatted")
    return out.getvalue()


CORE = ["block_md5", "classify_blocks", "dirty_regions", "dirty_regions_stitched", "plasma_regions", "dirty_share", "adler_blocks", "container_offsets", "chunk_fill", "extents", "gather_pack", "gather_cutline", "text_blocks", "stream_blocks", "stencil_step", "touched_then_hash", "parity_cells"]


@pytest.mark.parametrize("name", CORE)
def test_no_python_and_no_single_task(spark, sf_dir, name):
    text = plan(catalogue.QUERIES[name](spark, sf_dir))
    assert not re.search("Python|Pandas|Arrow|CartesianProduct|BroadcastNestedLoopJoin", text)
    if name not in ("dirty_share",):  # one row out of all
        assert "SinglePartition" not in text


def test_scans_are_pruned(spark, sf_dir):
    text = plan(catalogue.QUERIES["block_md5"](spark, sf_dir))
    assert set(re.findall(r"ReadSchema: struct<([^>]*)>", text)) == {"event_id:bigint,ts:timestamp_ntz,value:double"}
    text = plan(catalogue.QUERIES["invalid_blocks"](spark, sf_dir))
    assert "LessThanOrEqual(ts" in text


def test_payloads_stop_before_the_ledger_join(spark, sf_dir):
    text = plan(catalogue.QUERIES["classify_blocks"](spark, sf_dir))
    exchanged = re.findall(r"Exchange\nInput \[\d+\]: \[([^\]]*)\]", text)
    assert exchanged and not any("payload" in e for e in exchanged)


def test_nothing_imports_the_text_operators():
    for source in (ROOT / "blockdelta").rglob("*.py"):
        if "llm" not in source.relative_to(ROOT).parts:
            assert not re.search(r"import.*\bllm\b|from.*\bllm\b", source.read_text()), source


def test_entry_works_without_the_text_operators(tmp_path):
    import shutil

    shutil.copytree(ROOT / "blockdelta", tmp_path / "blockdelta", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(ROOT / "__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 80 and set(o) <= set(q) and 'pipeline' not in q"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
