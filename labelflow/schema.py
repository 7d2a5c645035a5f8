"""Frame contracts, checked by name and type at the boundary."""

from __future__ import annotations

from pyspark.sql import DataFrame

CONTRACTS = {
    "nodes": {"node": "bigint", "kind": "string", "key": "string"},
    "edges": {"src": "bigint", "dst": "bigint", "w": "double"},
    "scores": {"node": "bigint", "label": "bigint", "score": "double"},
    "gold": {"node": "bigint", "label": "bigint"},
    "cells": {"node": "bigint", "cell": "int", "val": "double"},
    "communities": {"node": "bigint", "community": "string"},
}


def require(df: DataFrame, contract: str) -> DataFrame:
    """``df`` with the contract's columns in order; raises ValueError if one is absent or of another type."""
    want, have = CONTRACTS[contract], dict(df.dtypes)
    wrong = [f"{c} {t} (found {have.get(c, 'nothing')})" for c, t in want.items() if have.get(c) != t]
    if wrong:
        raise ValueError(f"not a frame of {contract}: expected {', '.join(wrong)}")
    return df.select(*want)
