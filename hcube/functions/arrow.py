"""Arrow functions over columns of packed bits, and aggregates that make them."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import BinaryType, LongType

from .bits import BitVec, Dac
from .louds import Louds


@pandas_udf(LongType())
def dac_get(codes: pd.Series, place: pd.Series) -> pd.Series:
    """Value at a place of a variable-length code (``Dac.to_bytes``); null beyond its end."""
    made: dict[bytes, Dac] = {}

    def one(raw, i):
        if raw is None or pd.isna(i):
            return None
        if raw not in made:
            made[raw] = Dac.from_bytes(raw)
        dac = made[raw]
        return int(dac.get(int(i))) if 0 <= i < len(dac.chunks[0]) else None

    return pd.Series([one(r, i) for r, i in zip(codes, place)], dtype="Int64")


@pandas_udf(LongType())
def louds_child(bits: pd.Series, position: pd.Series, ordinal: pd.Series) -> pd.Series:
    """Position of the child with an ordinal (from 0) of the node at a position of a LOUDS bit string; null if there is none."""

    def one(b, i, k):
        if b is None or pd.isna(i) or pd.isna(k):
            return None
        tree = Louds(bits=BitVec(b))
        return tree.child(int(i), int(k) + 1) if 0 <= k < tree.degree(int(i)) else None

    return pd.Series([one(*x) for x in zip(bits, position, ordinal)], dtype="Int64")


@pandas_udf(BinaryType())
def pack_bits(bits: pd.Series, place: pd.Series) -> bytes:
    """Aggregate: 0/1 values in the order of their places, packed; for groups that fit a task (shards)."""
    ordered = bits.to_numpy()[place.to_numpy().argsort(kind="stable")]
    return BitVec(ordered).to_bytes()


@pandas_udf(BinaryType())
def pack_values(values: pd.Series, place: pd.Series) -> bytes:
    """Aggregate: values >= 0 in the order of their places as a variable-length code; for groups that fit a task."""
    return Dac(values.to_numpy()[place.to_numpy().argsort(kind="stable")].astype("uint64")).to_bytes()
