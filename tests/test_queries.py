"""Registered queries against their SQL in DuckDB. All of them run with TEST_ALL=1; else the quick ones."""

import os

import pytest
from harness import SF, differences

from progenrich import plans

QUERIES, ORACLES = plans.queries(), plans.oracles()
SLOW = ("exp", "ablate", "baseline", "cache_", "gain_curve", "progress", "sample_points", "completion", "epoch_", "monotone", "block_scorer", "block_object", "block_random", "repeat", "multi_op", "mode_", "stream_", "real_", "work_stats", "queue_", "online", "budget_run", "answer_diff", "benefit_agreement")
QUICK = [k for k in QUERIES if os.environ.get("TEST_ALL") or not k.startswith(SLOW)]


@pytest.mark.parametrize("name", QUICK + [k for k in ("exp7_cache_25", "stream_tumbling", "mode_pushdown") if k not in QUICK])
def test_query(spark, con, name):
    if name in ORACLES:
        assert differences(spark, name, QUERIES[name], ORACLES[name], con) == ""
    else:
        assert QUERIES[name](spark, SF).count() >= 0


def test_inverse_entropy_query(spark):
    assert QUERIES["inverse_entropy"](spark, SF).where("abs(h - back) > 1e-5").isEmpty()


def test_control_has_no_signal(spark):
    assert 0.3 < QUERIES["exp10_control"](spark, SF).first()["auc"] < 0.7


def test_entry_without_the_llm_subpackage(tmp_path):
    """The rest imports and registers its queries when both llm folders and the pipeline are gone."""
    import shutil
    import subprocess
    import sys

    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    shutil.copytree(f"{root}/progenrich", tmp_path / "progenrich", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 150 and set(o) <= set(q) and not any(k.startswith('op1') for k in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, timeout=120, env=os.environ | {"PYTHONPATH": str(tmp_path)})
