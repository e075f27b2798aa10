import subprocess
import sys
from pathlib import Path

import __spark_entry__ as entry

ROOT = Path(__file__).resolve().parents[1]


def test_queries_and_oracles_agree_in_names():
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.queries()) > 80


def test_entry_runs(spark):
    assert entry.entry(spark).columns == ["id", "component"]


def test_imports_without_the_optional_part(tmp_path):
    """Without its folder and module, the entry still offers the graph queries."""
    for p in ROOT.iterdir():
        if p.name not in ("corpus_pipeline.py", "forkline", ".git"):
            (tmp_path / p.name).symlink_to(p)
    (tmp_path / "forkline").mkdir()
    for p in (ROOT / "forkline").iterdir():
        if p.name != "llm":
            (tmp_path / "forkline" / p.name).symlink_to(p)
    code = "import __spark_entry__ as e; q = e.queries(); assert 'pipeline' not in q and 'cc_unconditional' in q"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
