"""The driver's contract."""

from __future__ import annotations

import os
import shutil
import subprocess
import sys
from pathlib import Path

import pytest

import __spark_entry__ as entry

ROOT = Path(__file__).resolve().parent.parent


def test_names_agree_and_import_needs_no_session():
    code = "import __spark_entry__ as e; q, s = e.queries(), e.oracle_sql(); assert set(s) <= set(q) and len(q) > 100"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True)


def test_entry_has_rows(spark):
    df = entry.entry(spark)
    assert df.columns == ["doc_id"] and df.count() == 40


@pytest.mark.parametrize("pipeline_left", [False, True])
def test_without_the_llm_folders(tmp_path, pipeline_left):
    """The rest imports, and its queries are all there, whether or not the pipeline's file is found."""
    for name in ("gradsift", "__spark_entry__.py", *["corpus_pipeline.py"] * pipeline_left):
        src = ROOT / name
        copy = shutil.copytree if src.is_dir() else shutil.copy
        copy(src, tmp_path / name)
    shutil.rmtree(tmp_path / "gradsift/llm", ignore_errors=True)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 100 and 'pipeline' not in q and not any(n.startswith('op') for n in q), sorted(q)"
    for path in (str(tmp_path), f"{tmp_path}{os.pathsep}{ROOT}"):
        subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=os.environ | {"PYTHONPATH": path}, check=True)


def test_a_fault_in_the_operators_shows(tmp_path):
    for name in ("gradsift", "__spark_entry__.py"):
        src = ROOT / name
        (shutil.copytree if src.is_dir() else shutil.copy)(src, tmp_path / name)
    folder = tmp_path / "gradsift/llm"
    folder.mkdir(exist_ok=True)
    (folder / "__init__.py").write_text("")
    (folder / "queries.py").write_text("import a_module_that_is_not_there\n")
    done = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; e.queries()"], cwd=tmp_path, env=os.environ | {"PYTHONPATH": str(tmp_path)}, capture_output=True, text=True, check=False)
    assert done.returncode and "a_module_that_is_not_there" in done.stderr
