"""The scalar methods as SQL functions of a session."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Name and definition (fixed signatures).
_FUNCTIONS = {
    "norm_text(t STRING) RETURNS STRING": r"trim(regexp_replace(lower(t), '[^\\p{L}\\p{N}]+', ' '))",
    "char_grams(t STRING, n INT) RETURNS ARRAY<STRING>": "get(transform(array(norm_text(t)), s -> array_distinct(filter(transform(sequence(1, greatest(length(s), 1)), i -> substring(s, i, n)), g -> length(g) = n))), 0)",
    "gram_overlap(q STRING, t STRING, n INT) RETURNS DOUBLE": "size(array_intersect(char_grams(q, n), char_grams(t, n))) / nullif(size(char_grams(q, n)), 0)",
    "edit_similarity(a STRING, b STRING) RETURNS DOUBLE": "CASE WHEN greatest(length(a), length(b)) = 0 THEN 1D ELSE 1 - levenshtein(a, b) / greatest(length(a), length(b)) END",
    "keyed_uniform(k STRING, salt STRING) RETURNS DOUBLE": "cast(conv(substring(md5(concat(salt, '|', k)), 1, 8), 16, 10) AS BIGINT) / 4294967296D",
}


def register(spark: SparkSession) -> list[str]:
    """Create them as temporary functions; gives their names."""
    for signature, body in _FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {signature} RETURN {body}")
    return [s.split("(")[0] for s in _FUNCTIONS]
