"""Comparison of results."""

from __future__ import annotations


def normal(value):
    import numpy as np

    if isinstance(value, np.ndarray):
        value = value.tolist()
    return tuple(normal(x) for x in value) if isinstance(value, (list, tuple)) else value


def same_rows(df, relation) -> None:
    """Equal columns and equal rows in any order."""
    columns = sorted(df.columns)
    assert columns == sorted(relation.columns)
    order = [relation.columns.index(c) for c in columns]
    got = sorted((tuple(normal(r[c]) for c in columns) for r in df.collect()), key=repr)
    want = sorted((tuple(normal(r[i]) for i in order) for r in relation.fetchall()), key=repr)
    assert got == want
