"""The driver's contract."""

import __spark_entry__ as contract


def test_names():
    names = contract.queries()
    assert set(contract.oracle_sql()) <= set(names)
    if contract.llm:
        assert all(any(n.startswith(f"op{i}_") for n in names) for i in range(1, 11)) and "pipeline" in names


def test_entry(spark):
    found = contract.entry(spark)
    rows = found.collect()
    assert len(rows) == 21 and all(x.samples > 0 for x in rows)


def test_without_the_subpackage(tmp_path):
    """Without llm and corpus_pipeline the entry still imports and has the engine's queries."""
    import shutil
    import subprocess
    import sys

    root = contract.ROOT
    shutil.copytree(f"{root}/subwin", tmp_path / "subwin", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{root}/__spark_entry__.py", tmp_path)
    code = "import __spark_entry__ as e; assert e.llm is None and len(e.queries()) > 100 and not any(k.startswith('op') for k in e.queries())"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={"PATH": "/usr/bin:/bin", "PYTHONPATH": str(tmp_path)})
