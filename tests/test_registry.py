import subprocess
import sys
from pathlib import Path

ROOT = Path(__file__).resolve().parents[1]


def test_entry_names_agree():
    sys.path.insert(0, str(ROOT))
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_library_does_not_import_training_data_operators():
    code = "import sys; sys.modules['tabseek.llm'] = None; import tabseek.workloads as w; assert w.queries()"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)
