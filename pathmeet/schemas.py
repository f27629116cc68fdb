"""Fixed schemas of the engine's relations."""

from __future__ import annotations

from pyspark.sql import types as T

L, B, S = T.LongType(), T.BooleanType(), T.StringType()


def _of(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


EDGES = _of(src=L, dst=L)
WEIGHTED_EDGES = _of(src=L, dst=L, w=L)
QUERIES = _of(qid=L, s=L, t=L)
ANSWERS = _of(qid=L, s=L, t=L, dist=L, case=S, witness=L, probes=L, lower=L, upper=L, certified=B)

#: Kinds of nodes; a node id is the key of its row times 16 plus the kind.
KINDS = {"customer": 0, "supplier": 1, "part": 2, "order": 3, "nation": 4, "region": 5, "user": 6, "event_type": 7, "document": 8, "vector": 9, "page": 10, "path": 11, "turn": 12, "item": 13}


def require(df, schema: T.StructType, what: str):
    """``df`` cast to ``schema``; raises if a column is missing."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"{what} lacks {missing}; it needs {schema.simpleString()}")
    return df.select(*(df[f.name].cast(f.dataType) for f in schema))
