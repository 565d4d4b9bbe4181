from __future__ import annotations

import pytest

from rowloom.llm.queries import tokenizer_path

LONG = ("under the MIT License word%d and more " * 3000) % tuple(range(3000))
TEXTS = [
    None, "", "   \n\t ", "a", "one two three", "The QUICK brown fox jumps over the lazy dog again", "The QUICK brown fox jumps over the lazy dog again",
    "Ünïcödé ▁ marks  and   spaces ", "\x00 zero byte", "idiot scum pathetic stupid loser", LONG, LONG, "x" * 5000,
    "Licensed under CC BY-NC 4.0. Released under the MIT License.", "Apache License, Version 2.0",
]


@pytest.fixture(scope="session")
def odd_docs(spark):
    """Nulls, empty, long and repeated texts, repeated and null ids, and columns with clashing names."""
    rows = [(i, t, "en", "src0", None if t is None else len(t), 1, "x", "y") for i, t in enumerate(TEXTS)]
    rows += [(5, TEXTS[5], "en", "src0", 1, 1, "x", "y"), (None, "no id at all here", None, None, None, None, None, None)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, label int, key string, score string"
    return spark.createDataFrame(rows, schema)


@pytest.fixture(scope="session")
def no_docs(odd_docs):
    return odd_docs.where("false")


@pytest.fixture(scope="session")
def model_path():
    return tokenizer_path()


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")
