"""The engine's roles as SQL functions: temporary ones of the session, expanded into the plan, no Python at run time."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: name -> (arguments, result, body) of scalar functions.
SCALARS = {
    "element_digest": ("payload string", "bigint", "xxhash64(payload)"),
    "element_digest_portable": ("payload string", "bigint", "cast(conv(substring(md5(payload), 1, 15), 16, 10) as bigint)"),
    "slice_bits": ("n bigint", "bigint", "cast(ceil(n / 0.6931471805599453D) as bigint)"),
    "slice_pos": ("digest bigint, phase bigint, slice bigint, m bigint", "bigint", "pmod(xxhash64(digest, phase, slice), m)"),
    "slice_pos_portable": (
        "digest bigint, phase bigint, slice bigint, m bigint",
        "bigint",
        "pmod(cast(conv(substring(md5(concat_ws(':', cast(digest as string), cast(phase as string), cast(slice as string))), 1, 15), 16, 10) as bigint), m)",
    ),
    "cell_check": ("digest bigint", "bigint", "xxhash64(digest, 1000003L)"),
    "cell_is_pure": ("id_xor bigint, check_xor bigint, cnt bigint", "boolean", "abs(cnt) = 1 and xxhash64(id_xor, 1000003L) = check_xor"),
    "difference_per_side": ("n bigint, similarity_pct double", "bigint", "cast(floor(n * (1 - similarity_pct / 100) / (1 + similarity_pct / 100) + 0.5D) as bigint)"),
}

#: name -> (arguments, columns, query) of table functions.
TABLES = {
    "slice_positions": (
        "digest bigint, phase bigint, last_slice bigint, m bigint",
        "slice bigint, pos bigint",
        "select s, pmod(xxhash64(digest, phase, s), m) from (select explode(sequence(0L, last_slice)) as s)",
    ),
}


def register(spark: SparkSession) -> None:
    """Makes all functions known to the session; calling it again replaces them."""
    for name, (args, result, body) in SCALARS.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {result} return {body}")
    for name, (args, columns, query) in TABLES.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns table({columns}) return {query}")
