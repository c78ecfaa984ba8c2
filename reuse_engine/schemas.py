"""Declared columns of the stored tables between stages, and a check of a table against them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import StructType

#: Table: columns and types that every producer gives; a table may have more.
TABLES = {
    "artifacts": "artifact_id string, corpus string, origin string, creator string, bundle_id string, deployed_us bigint, payload string, volume_milli bigint",
    "normalized": "artifact_id string, corpus string, origin string, creator string, bundle_id string, deployed_us bigint, volume_milli bigint, "
    "raw_hash string, runtime string, runtime_hash string, tok string, token_hash string, had_prefix boolean, had_trailer boolean",
    "units": "corpus string, origin string, token_hash string, unit_id string, n_dup bigint, n_runtime bigint, n_creators bigint, creator string, "
    "first_seen_us bigint, tok string, n_bytes bigint",
    "fingerprints": "corpus string, origin string, unit_id string, token_hash string, n_dup bigint, creator string, first_seen_us bigint, fp string, fp_len int, "
    "n_ops bigint, n_pieces bigint, n_distinct_ops bigint, n_terminators bigint, n_operand_bytes bigint, n_bytes bigint",
    "pairs": "corpus string, origin string, a string, b string, la int, lb int, dist int, max_len int, score_bp bigint",
    "clusters": "unit_id string, cluster_id string",
    "findings": "unit_id string, ftype string, n bigint",
    "members": "bundle_id string, unit_id string",
    "bundles": "bundle_id string, owner string, deployed_us bigint, volume_milli bigint",
    "clones": "ua string, ub string, n_a bigint, n_b bigint, total_bp bigint, sim_ab_bp bigint, sim_ba_bp bigint, sim_bp bigint",
}


def schema_of(table: str) -> StructType:
    return StructType.fromDDL(TABLES[table])


def conform(df: DataFrame, table: str) -> DataFrame:
    """``df``, if it has the declared columns of ``table``; an error names what is missing or of another type."""
    has = {f.name: f.dataType for f in df.schema}
    wrong = [f"{f.name} {f.dataType.simpleString()} (is {has[f.name].simpleString() if f.name in has else 'missing'})" for f in schema_of(table) if has.get(f.name) != f.dataType]
    if wrong:
        raise TypeError(f"not a table of {table}: {', '.join(wrong)}")
    return df
