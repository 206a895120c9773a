"""Schemas of the state tables, and a check on entry."""

from __future__ import annotations

from pyspark.sql import DataFrame

SCHEMAS = {
    "tokens": {"doc_id": "bigint", "pos": "bigint", "word_id": "bigint"},
    "tokens_z": {"doc_id": "bigint", "pos": "bigint", "word_id": "bigint", "z": "int"},
    "theta": {"doc_id": "bigint", "topic": "int", "n": "bigint"},
    "phi": {"word_id": "bigint", "topic": "int", "n": "bigint"},
    "psi": {"topic": "int", "n": "bigint"},
    "alpha": {"topic": "int", "alpha": "double"},
    "vocab": {"word": "string", "word_id": "bigint", "tf": "bigint", "df": "bigint"},
}


def checked(df: DataFrame, name: str) -> DataFrame:
    """df with the columns of a state table, in order; an error names what is missing or of another type."""
    have = dict(df.dtypes)
    wrong = {c: have.get(c) for c, t in SCHEMAS[name].items() if have.get(c) != t}
    if wrong:
        raise TypeError(f"{name} needs {SCHEMAS[name]}; got {wrong}")
    return df.select(*SCHEMAS[name])
