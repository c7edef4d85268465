"""Fixed record types of the engine."""

from __future__ import annotations

from pyspark.sql import types as T

_S, _L, _I, _D = T.StringType(), T.LongType(), T.IntegerType(), T.DoubleType()


def _row(**fields) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


RECORD = _row(record_id=_S, kind=_S, path=_S, mime=_S, ext=_S, title=_S, text=_S, ts=T.TimestampType(), seq=_L)
CHUNK = _row(doc_id=_L, chunk_no=_I, p_start=_I, p_end=_I, o_start=_I, o_end=_I, header=_S, text=_S)
VARIANT = _row(alias=_S, count=_I, confidence=_D, source=_S, snippets=T.ArrayType(_S))
CONTEXT = _row(type=_S, value=_S, confidence=_D, source_text=_S)
ENTITY = _row(doc_id=_L, chunk_no=_I, ent_id=_S, type=_S, name=_S, aliases=T.ArrayType(_S), variants=T.ArrayType(VARIANT), context=T.ArrayType(CONTEXT),
              props=T.MapType(_S, _S), confidence=_D, fingerprint=_S, dedup_status=_S)
RELATION = _row(doc_id=_L, chunk_no=_I, src=_S, dst=_S, rel_type=_S, quals=T.MapType(_S, _S), evidence=_S, confidence=_D, ord=_L)
CLASS = _row(class_id=_L, label=_S, alt_labels=T.ArrayType(_S), definition=_S, vec=T.ArrayType(T.FloatType()), pr=_D)
SUBCLASS = _row(child=_S, parent=_S)
PREDICATE = _row(pred_id=_S, label=_S, definition=_S, domain=_S, range=_S, inverse_of=_S)
PAIR = _row(left_id=_S, right_id=_S, score=_D, reason=_S, delta=_I, n_shared=_I, action=_S, verdict=_S, confidence=_S)
PLAN = _row(sheet=_S, entity_type=_S, name_column=_S, columns=T.ArrayType(_row(name=_S, kind=_S, prop=_S)), relations=T.ArrayType(_row(column=_S, rel_type=_S, target_type=_S)),
            drop_where=_S, split_columns=T.ArrayType(_S), fill_columns=T.ArrayType(_S))
RESULT = _row(object_id=_S, entities=T.ArrayType(ENTITY), relationships=T.ArrayType(RELATION), dedup_candidates=T.ArrayType(PAIR), coverage_warnings=T.ArrayType(_S),
              envelope=_row(source_file=_S, mime=_S, processed_ts=T.TimestampType()))
