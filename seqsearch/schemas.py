"""Fixed schemas; nothing is inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import StructType, _parse_datatype_string

SEQ = "seq_id bigint, class_id string, instance_id int, tokens array<int>, times array<double>, len int"
POSTING = "seq_id bigint, word int, cnt bigint"
PAIR = "query_id bigint, cand_id bigint"
RANKED = "query_id bigint, rank int, cand_id bigint, score double"
FRAME = "clip_id bigint, t int, pose array<array<double>>"
LATENT = "clip_id bigint, t int, latent array<double>"
PATCH = "clip_id bigint, patch_idx int, vec array<double>"
CODEBOOK = "code int, centroid array<double>, ema_n double, ema_m array<double>, epoch int"
ASSIGNED = "clip_id bigint, patch_idx int, code int, dist2 double"


def validate(df: DataFrame, ddl: str) -> DataFrame:
    """``df`` with exactly the columns of the schema, in its order; wrong or missing columns raise."""
    wanted = _parse_datatype_string(ddl)
    assert isinstance(wanted, StructType)
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    wrong = {f.name: have.get(f.name) for f in wanted if have.get(f.name) != f.dataType.simpleString()}
    if wrong:
        raise ValueError(f"columns that don't fit the schema: {wrong}")
    return df.select(*[f.name for f in wanted])
