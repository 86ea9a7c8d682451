"""The methods in SQL: temporary SQL functions (inlined by Catalyst, no Python), a table function, and views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from .randomness import HALF, MASK, STEP

_MULTIPLIER = "CAST(conv(substr(md5(concat_ws(':', seed, rnd, tag)), {at}, 7), 16, 10) AS BIGINT)"
FUNCTIONS = {
    "feature_code(name STRING) RETURNS BIGINT": "CAST(conv(substr(md5(name), 1, 15), 16, 10) AS BIGINT)",
    "mixed_code(code BIGINT, seed BIGINT, rnd INT, tag STRING) RETURNS BIGINT": f"shiftright((shiftright(code, 30) ^ {_MULTIPLIER.format(at=1)}) * ({_MULTIPLIER.format(at=8)} | 1) + (code & {HALF}) * ({_MULTIPLIER.format(at=15)} | 1), 20) & {MASK}",
    "stepped(x BIGINT) RETURNS BIGINT": f"shiftright((x ^ shiftright(x, 15)) * {STEP}, 15) & {MASK}",
    "unit_draw(code BIGINT, seed BIGINT, rnd INT, tag STRING) RETURNS DOUBLE": "(stepped(mixed_code(code, seed, rnd, tag)) + 0.5D) / 2147483648D",
    "gamma2_draw(code BIGINT, seed BIGINT, rnd INT, tag STRING) RETURNS DOUBLE": "-ln(unit_draw(code, seed, rnd, concat(tag, '1')) * unit_draw(code, seed, rnd, concat(tag, '2')))",
    "sample_score(weight DOUBLE, p DOUBLE, g DOUBLE, c DOUBLE, b DOUBLE) RETURNS DOUBLE": "ln(c) - g * (floor(p * ln(weight) / g + b) + 1 - b)",
    "jaccard_sets(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE": "size(array_intersect(a, b)) / nullif(size(array_union(a, b)), 0)",
    "minmax_kernel(a MAP<STRING, DOUBLE>, b MAP<STRING, DOUBLE>, p DOUBLE) RETURNS DOUBLE": "aggregate(map_values(map_zip_with(a, b, (k, x, y) -> pow(least(coalesce(x, 0D), coalesce(y, 0D)), p))), 0D, (s, x) -> s + x) / nullif(aggregate(map_values(map_zip_with(a, b, (k, x, y) -> pow(greatest(coalesce(x, 0D), coalesce(y, 0D)), p))), 0D, (s, x) -> s + x), 0D)",
}


def register(spark: SparkSession) -> list[str]:
    """Create the functions in the session; their names."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("signature_slots", SignatureSlots)
    return [*[h.split("(")[0] for h in FUNCTIONS], "signature_slots"]


@udtf(returnType="slot int, code long, level long")
class SignatureSlots:
    """signature_slots(codes, weights, length, p, seed): the weighted sampler's slots of one vector as rows."""

    def eval(self, codes, weights, length: int, p: float, seed: int):
        import numpy as np

        from cohort_engine.operators.hashing import Sparse, weighted_winners

        if codes:
            s = Sparse(np.array(codes, np.int64), np.array(weights, float), np.array([0, len(codes)]))
            at, level = weighted_winners(s, list(range(1, length + 1)), float(p), int(seed))
            for k in range(length):
                yield k + 1, int(s.code[at[0, k]]), int(level[0, k])


class CohortSession:
    """SQL over cohorts: the views ``cohorts``, ``cohort_identity`` and ``campaign_recall`` and the functions above."""

    def __init__(self, spark: SparkSession, assign: DataFrame, identity: DataFrame | None = None, recall: DataFrame | None = None):
        self.spark = spark
        register(spark)
        for name, df in (("cohorts", assign), ("cohort_identity", identity), ("campaign_recall", recall)):
            if df is not None:
                df.createOrReplaceTempView(name)

    def sql(self, text: str) -> DataFrame:
        return self.spark.sql(text)
