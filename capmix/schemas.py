"""The contracts between modules, and their validation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

_L, _S, _D, _I, _B = T.LongType(), T.StringType(), T.DoubleType(), T.IntegerType(), T.BooleanType()
_V = T.ArrayType(_D)


def _schema(*fields: tuple) -> T.StructType:
    return T.StructType([T.StructField(*f) for f in fields])


POOL = _schema(("pair_id", _L), ("image_id", _L), ("raw_text", _S), ("lang", _S), ("source", _S))
CAPTION_SHEET = _schema(("pair_id", _L), ("captioner", _S), ("temperature", _D), ("text", _S))
VECTOR_SHEET = _schema(("key", _L), ("kind", _S), ("vec", _V))
SCORE_SHEET = _schema(("pair_id", _L), ("image_id", _L), ("raw_sim", _D), ("gen_sim", _D), ("cid", _I), ("gated", _B))
SELECTION = _schema(("pair_id", _L), ("image_id", _L), ("origin", _S), ("sim", _D))
METRIC = _schema(("recipe", _S), ("scale", _S), ("metric", _S), ("value", _D), ("n", _L))


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df, if it has every column of schema with its type; an error that names what is wrong if not."""
    have = {f.name: f.dataType for f in df.schema}
    wrong = [f"{f.name}: {'missing' if f.name not in have else f'{have[f.name].simpleString()}, not {f.dataType.simpleString()}'}" for f in schema if have.get(f.name) != f.dataType]
    if wrong:
        raise ValueError("schema mismatch: " + "; ".join(wrong))
    return df
