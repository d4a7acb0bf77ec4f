import pathlib
import shutil
import subprocess
import sys

import pytest

ROOT = pathlib.Path(__file__).resolve().parent.parent
CORE = "import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); assert len(q) > 120 and set(s) <= set(q) and 'pipeline' not in q and not [n for n in q if n.startswith('op')]"


@pytest.mark.parametrize("pipeline", [True, False])
@pytest.mark.parametrize("caches", [True, False])
def test_the_rest_works_without_the_llm_folders(tmp_path, pipeline, caches):
    """The whole repository without both folders: with and without the pipeline's file, and with a folder left of caches only."""
    repo = tmp_path / "repo"
    shutil.copytree(ROOT, repo, ignore=shutil.ignore_patterns(".git", "__pycache__", "spark-warehouse", "metastore_db"))
    shutil.rmtree(repo / "vistapoint/llm"), shutil.rmtree(repo / "tests/llm")
    if caches:
        (repo / "vistapoint/llm/__pycache__").mkdir(parents=True)
    if not pipeline:
        (repo / "corpus_pipeline.py").unlink()
    subprocess.run([sys.executable, "-c", CORE], cwd=repo, check=True, env={"PATH": "/usr/bin:/bin"})
    if pipeline and not caches:
        subprocess.run([sys.executable, "-m", "pytest", "tests", "-q", "-x", "-p", "no:cacheprovider", "--ignore", "tests/test_entry.py", "-k", "circular_difference or borders_count or validation"], cwd=repo, check=True)


def test_a_fault_inside_the_llm_subpackage_is_not_hidden(tmp_path):
    repo = tmp_path / "repo"
    shutil.copytree(ROOT, repo, ignore=shutil.ignore_patterns(".git", "__pycache__", "tests"))
    (repo / "vistapoint/llm/tokens.py").write_text("import no_such_module\n")
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; e.queries()"], cwd=repo, capture_output=True, text=True, env={"PATH": "/usr/bin:/bin"})
    assert done.returncode and "no_such_module" in done.stderr


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).columns == ["rank", "cell_x", "cell_y", "ci"]
