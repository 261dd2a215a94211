"""Relations of the engine.  Axes are rows, not columns, so each target may have its own."""

from __future__ import annotations

from pyspark.sql.types import ArrayType, BooleanType, ByteType, DateType, DoubleType, IntegerType, LongType, StringType, StructField, StructType


def _of(**fields) -> StructType:
    return StructType([StructField(name, kind) for name, kind in fields.items()])


_S, _L, _I, _D = StringType(), LongType(), IntegerType(), DoubleType()
ITEMS = _of(item_id=_L, title=_S, body=_S, venue=_S, fields=ArrayType(_S), authors=ArrayType(_S), pub_date=DateType(), year=_I, ref_count=_I, cite_count=_I, influential=_I, open_access=BooleanType(), url=_S, journal=_of(name=_S, volume=_S, pages=_S))
LINKS = _of(src=_L, dst=_L, relevance=_D)
NETWORK = _of(target_id=_L, item_id=_L, relation=_S, layer=_I, relevance=_D)
FEATURES = _of(item_id=_L, axis=_S, kind=_S, direction=_I, v_num=_D, v_txt=_S)
AXES = _of(target_id=_L, axis=_S, kind=_S, direction=_I, tolerance=_D, unit=_S, t_num=_D, t_txt=_S, origin=_S)
CLAIMS = _of(target_id=_L, item_id=_L, relation=_S, layer=_I, axis=_S, kind=_S, direction=_I, tolerance=_D, t_num=_D, t_txt=_S, v_num=_D, v_txt=_S)
DUELS = _of(target_id=_L, item_id=_L, relation=_S, layer=_I, axis=_S, s=_I, why=_S)
EDGES = _of(src=_L, dst=_L, conf=ByteType(), gap=_I, sigma=_D)
CALLS = _of(stage=_S, prompt_hash=_S, model=_S, n_in=_L, n_out=_L, seconds=_D, cached=BooleanType(), vote=_I)
EDITS = _of(op=_S, axis=_S, new_axis=_S, kind=_S, direction=_I, weight=_D)
