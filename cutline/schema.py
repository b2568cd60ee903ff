"""Fixed schemas of the engine's tables, and the check at module borders."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T


def _struct(text: str) -> T.StructType:
    return T.StructType.fromDDL(text)


NODES = _struct("node_id bigint, x bigint, y bigint")
EDGES = _struct("u bigint, v bigint")
METRIC = _struct("u bigint, v bigint, weight bigint")
RANKS = _struct("node_id bigint, rank bigint")
INDEX_ARCS = _struct("lo bigint, hi bigint, is_shortcut boolean")
WEIGHTS = _struct("lo bigint, hi bigint, up bigint, down bigint")
CUTS = _struct("cell_id bigint, cutter int, step int, size bigint, small bigint, n bigint, grown string, rule string")
PAIRS = _struct("pair_id bigint, s bigint, t bigint")


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df's columns of the schema; an error that names what is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema}
    wrong = [f"{f.name}: {f.dataType.simpleString()} (got {have[f.name].simpleString() if f.name in have else 'none'})" for f in schema if have.get(f.name) != f.dataType]
    if wrong:
        raise TypeError("; ".join(wrong))
    return df.select(*[f.name for f in schema])
