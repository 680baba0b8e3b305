import subprocess
import sys

import __spark_entry__ as entry


def test_names_and_oracles_agree():
    q, o = entry.queries(), entry.oracle_sql()
    assert set(o) <= set(q) and len(q) > 100


def test_entry_runs(spark):
    d = entry.entry(spark)
    assert d.columns == ["group_rank", "image_rank", "xdim", "ydim", "zdim", "slab", "score"] and d.count() == 20


def test_works_without_the_llm_folders(tmp_path):
    import os
    import shutil

    root = os.path.dirname(os.path.abspath(entry.__file__))
    shutil.copytree(f"{root}/cubelens", tmp_path / "cubelens", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 100 and not any(k.startswith('op') for k in q)"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})


def test_a_broken_subpackage_is_not_hidden(tmp_path):
    import os
    import shutil

    root = os.path.dirname(os.path.abspath(entry.__file__))
    shutil.copytree(f"{root}/cubelens", tmp_path / "cubelens", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    (tmp_path / "cubelens" / "llm").mkdir()
    env = {**os.environ, "PYTHONPATH": str(tmp_path)}
    run = lambda code: subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=env, capture_output=True, text=True)
    assert run("import __spark_entry__ as e; assert len(e.queries()) > 100").returncode == 0  # only an empty folder is left
    (tmp_path / "cubelens" / "llm" / "queries.py").write_text("import surely_no_such_module")
    assert "surely_no_such_module" in run("import __spark_entry__ as e; e.queries()").stderr


def test_no_shared_folder_is_an_error_on_a_cluster():
    import pytest

    from cubelens import storage

    class Cluster:
        class conf:
            get = staticmethod(lambda key, default: default)

        class sparkContext:
            master = "spark://somewhere:7077"

    with pytest.raises(RuntimeError):
        storage.shared_dir(Cluster)
    Cluster.sparkContext.master = "local[4]"
    assert storage.shared_dir(Cluster) == storage.FALLBACK_DIR


def test_sql_functions(spark):
    from cubelens import sql

    sql.register(spark)
    assert spark.sql("SELECT heat_red(6, 4) AS r, heat_blue(2, 4) AS b").first()[:] == (0.5, 0.5)
    assert spark.sql("SELECT count(*) FROM triples(8)").first()[0] == 56
    assert spark.sql("SELECT count(DISTINCT owner) FROM work_plan(8, 16, 64)").first()[0] == 8
