"""The driver's contract."""

import re
from pathlib import Path

import __spark_entry__ as entry

ROOT = Path(__file__).resolve().parents[1]


def test_registries_agree():
    names = set(entry.queries())
    assert set(entry.oracle_sql()) <= names and len(names) > 100
    if entry.HAS_LLM:
        assert {int(m[1]) for n in names if (m := re.match(r"op(\d+)_", n))} == set(range(1, 11))
    assert ("pipeline" in names) == entry.HAS_PIPELINE


def test_entry_has_rows(spark):
    assert entry.entry(spark).count() == 1


def test_nothing_outside_imports_the_llm_operators():
    for path in (ROOT / "epsgraph").rglob("*.py"):
        if "llm" not in path.relative_to(ROOT).parts:
            assert not re.search(r"import.*\bllm\b|from.*\bllm\b", path.read_text()), path
