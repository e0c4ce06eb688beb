"""The entry without the subpackage of the ten operators: everything else is registered and runs."""

import os
import shutil
import subprocess
import sys

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))

PROGRAM = """
import __spark_entry__ as e
names, sql = set(e.queries()), set(e.oracle_sql())
assert "draw_sweep_10" in names and not any(n.startswith("op") or n == "pipeline" for n in names | sql), names
assert sql <= names
"""


def test_entry_without_the_subpackage(tmp_path):
    for keep in ([], ["corpus_pipeline.py"]):
        top = tmp_path / f"copy{len(keep)}"
        shutil.copytree(os.path.join(ROOT, "facetsel"), top / "facetsel", ignore=shutil.ignore_patterns("llm", "__pycache__"))
        for name in ("__spark_entry__.py", *(x for x in keep if os.path.exists(os.path.join(ROOT, x)))):
            shutil.copy(os.path.join(ROOT, name), top / name)
        env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
        done = subprocess.run([sys.executable, "-c", PROGRAM], cwd=top, env=env, capture_output=True, text=True, timeout=300)
        assert done.returncode == 0, done.stderr
