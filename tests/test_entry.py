"""The entry module imports without a session, and every SQL twin has its query."""

import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_imports_without_a_session():
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert set(o) <= set(q) and len(q) > 80; print(len(q))"
    assert subprocess.run([sys.executable, "-c", code], cwd=ROOT, capture_output=True, check=True).stdout


def test_imports_without_the_training_data_folders(tmp_path):
    (tmp_path / "__spark_entry__.py").symlink_to(ROOT / "__spark_entry__.py")
    (tmp_path / "localcomm").mkdir()
    for p in (ROOT / "localcomm").iterdir():
        if p.name != "llm":
            (tmp_path / "localcomm" / p.name).symlink_to(p)
    code = "import sys; sys.path.insert(0, '.'); import __spark_entry__ as e; assert not [n for n in e.queries() if n.startswith('op')]"
    # A copy, as Python follows the link of the file it runs, not of those it imports.
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True)
