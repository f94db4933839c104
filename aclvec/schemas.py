"""Declared schemas; inputs are checked against them, not inferred."""

from __future__ import annotations

from pyspark.sql import DataFrame

SCHEMAS = {
    "ua": "user_id bigint, role_id int",
    "pa": "role_id int, doc_id bigint",
    "role_parent": "role_id int, parent_id int",
    "vectors": "vec_id bigint, doc_id bigint, embedding array<float>",
    "queries": "query_id bigint, user_id bigint, k int, qvec array<float>",
    "part_role": "partition_id int, role_id int",
    "part_doc": "partition_id int, doc_id bigint",
    "routing": "rs string, partition_id int",
    "trace": "step int, src int, dst int, role_id int, d_storage bigint, gain_r double, gain_u double, memory double, sbar double, ef double",
    "policy_changes": "seq bigint, ts timestamp, op string, user_id bigint, role_id int, doc_id bigint",
}


def checked(df: DataFrame, name: str) -> DataFrame:
    """`df` with the columns and types of a declared schema, in its order; a missing column or other type raises."""
    want = dict(part.strip().split(" ", 1) for part in SCHEMAS[name].split(", "))
    have = dict(df.dtypes)
    wrong = {c: (t, have.get(c)) for c, t in want.items() if have.get(c) != t}
    if wrong:
        raise TypeError(f"{name}: {wrong}")
    return df.select(*want)
