import shutil
import subprocess
import sys
from pathlib import Path

import __spark_entry__ as entry

ROOT = Path(entry.__file__).parent


def test_queries_and_sql_fit_together():
    queries, sql = entry.queries(), entry.oracle_sql()
    assert len(queries) > 200 and len(sql) > 140 and set(sql) <= set(queries)


def test_without_the_llm_folders(tmp_path):
    """A copy without that subpackage, its tests and the pipeline imports and lists the other queries."""
    for p in ROOT.rglob("*.py"):
        rel = p.relative_to(ROOT)
        if "llm" not in rel.parts and rel.name != "corpus_pipeline.py":
            (tmp_path / rel).parent.mkdir(parents=True, exist_ok=True)
            shutil.copy(p, tmp_path / rel)
            assert rel.parts[0] == "tests" or rel.name == "__spark_entry__.py" or "entitygraph.llm" not in p.read_text(), p
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 200 and set(e.oracle_sql()) <= set(q) and not any(n.startswith('op1_') or n == 'pipeline' for n in q); print('listed')"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True, timeout=120)
    assert done.stdout.strip() == "listed", done.stderr


def test_other_failed_imports_are_errors(tmp_path):
    for p in ROOT.rglob("*.py"):
        rel = p.relative_to(ROOT)
        (tmp_path / rel).parent.mkdir(parents=True, exist_ok=True)
        shutil.copy(p, tmp_path / rel)
    (tmp_path / "entitygraph/llm/packing.py").write_text("import a_module_that_is_not_there\n")
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; e.queries()"], cwd=tmp_path, capture_output=True, text=True, timeout=120)
    assert done.returncode and "a_module_that_is_not_there" in done.stderr
