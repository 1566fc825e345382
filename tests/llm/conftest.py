import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from tests_llm_prose import prose  # noqa: E402


#: Names that the operators use inside.
CLASHING = ["d", "k", "id", "line", "node", "token", "level", "fences", "_l", "_s", "_l2", "_f2", "_text", "_given", "_doc", "_key", "_runs", "_hash", "_own", "_node", "first", "removed_", "comp"]


@pytest.fixture(scope="session")
def docs_of(spark):
    """Documents with null ids, texts, languages and sources, empty and long texts, ties, repeated rows and a clashing extra column."""

    def make(texts, extra=True):
        rows = [(i, t, "en" if i % 3 else None, "s" if i % 2 else None, None if t is None else len(t), f"x{i}") for i, t in enumerate(texts)]
        if extra:
            rows += [(None, prose("null id", 40), None, None, 0, "y"), rows[0]]
        df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, g string")
        return df.selectExpr("*", *[f"'clash' AS `{c}`" for c in CLASHING]) if extra else df

    return make
