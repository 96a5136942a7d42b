"""Every query beside its SQL on the smallest tables; those without SQL must give rows."""

import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parent))
import oracle  # noqa: E402

from dpcluster import catalog  # noqa: E402

QUERIES, SQL = catalog.queries(), catalog.oracle_sql()
SLOW = {"exp_compare_small", "exp_hybrid_small", "exp_heatmap_small", "exp_hybrid_heatmap", "exp_runtime", "noisy_lloyd_t_sweep", "exp_init", "exp_range_fix", "exp_count_bias", "evolve_round_sweep"}


@pytest.fixture(scope="module")
def con(small):
    return oracle.database(small)


@pytest.mark.parametrize("name", [n for n in QUERIES if n in SQL])
def test_query_equals_sql(spark, small, con, name):
    assert oracle.differ(con, QUERIES[name](spark, small), SQL[name]) == ""


@pytest.mark.parametrize("name", [n for n in QUERIES if n not in SQL and n not in SLOW])
def test_query_gives_rows(spark, small, name):
    assert QUERIES[name](spark, small).count() > 0


READING = "align_lexicographic bias2_grid_table block_counts block_counts_3k block_noise_scale block_size_sweep centroid_mse_delta centroid_mse_empirical centroid_pairs centroids_as_arrays crossover eps_threshold_table".split()


@pytest.mark.parametrize("name", READING)
def test_query_needs_its_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        QUERIES[name](spark, str(tmp_path)).collect()


def test_entry_imports_without_the_training_data_operators(tmp_path):
    import subprocess

    home = Path(__file__).parents[1]
    for p in home.iterdir():
        if p.name not in ("corpus_pipeline.py", "dpcluster", ".git"):
            (tmp_path / p.name).symlink_to(p)
    (tmp_path / "dpcluster").mkdir()
    for p in (home / "dpcluster").iterdir():
        if p.name != "llm":
            (tmp_path / "dpcluster" / p.name).symlink_to(p)
    (tmp_path / "__spark_entry__.py").unlink()
    (tmp_path / "__spark_entry__.py").write_text((home / "__spark_entry__.py").read_text())
    code = "import __spark_entry__ as e; q = e.queries(); assert not any(k.startswith('op') or k == 'pipeline' for k in q), q; print(len(q))"
    got = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)}, capture_output=True, text=True)
    assert got.returncode == 0, got.stderr
    assert int(got.stdout) == len(QUERIES)
