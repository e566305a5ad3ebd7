"""The driver entry without the corpus parts."""

import os
import shutil
import subprocess
import sys

import pytest

from tests.conftest import ROOT

CHECK = """
import __spark_entry__ as e
q, o = e.queries(), e.oracle_sql()
assert "run_hier" in q and set(o) <= set(q)
assert not [n for n in q if n == "pipeline" or (n.startswith("op") and n[2].isdigit())]
"""


@pytest.mark.parametrize("pipeline_stays", [False, True])
def test_entry_without_the_corpus_folders(tmp_path, pipeline_stays):
    skip = shutil.ignore_patterns(".git", "__pycache__", "llm", *([] if pipeline_stays else ["corpus_pipeline.py"]))
    shutil.copytree(ROOT, tmp_path / "copy", ignore=skip)
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    done = subprocess.run([sys.executable, "-c", CHECK], cwd=tmp_path / "copy", env=env, capture_output=True, text=True, timeout=120)
    assert done.returncode == 0, done.stderr
