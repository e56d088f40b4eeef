import re
from pathlib import Path

ROOT = Path(__file__).resolve().parent.parent


def test_every_sql_has_a_query():
    from graphwatch import catalogue

    assert set(catalogue.oracle_sql()) <= set(catalogue.queries())


def test_nothing_else_imports_the_training_data_operators():
    for path in (ROOT / "graphwatch").rglob("*.py"):
        if "llm" not in path.parts:
            assert not re.search(r"graphwatch\.llm|from graphwatch import llm|corpus_pipeline", path.read_text()), path
