"""The methods' pieces as SQL functions: distances that stay in the JVM, and the block message as a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .methods import summarise
from .metrics import L1

#: Distances as SQL text over their two arguments.
DISTANCES = {
    "l1_distance": ("ARRAY<BIGINT>", "BIGINT", "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0L, (s, v) -> s + v)"),
    "l2_distance": ("ARRAY<DOUBLE>", "DOUBLE", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, v) -> s + v))"),
    "inversion_distance": ("BIGINT", "BIGINT", "CAST(bit_count(a ^ b) AS BIGINT)"),
}


class BlockMessage:
    """``fair_block_message(TABLE(points) PARTITION BY block, k)``: what a block sends under the l1 metric."""

    def __init__(self):
        self.rows, self.k = [], 0

    def eval(self, row, k: int):
        self.rows.append((row["block"], row["ord"], row["grp"], row["coords"]))
        self.k = k

    def terminate(self):
        import numpy as np

        if not self.rows:
            return
        ords, grps, X = np.array([r[1] for r in self.rows]), np.array([r[2] for r in self.rows]), np.array([r[3] for r in self.rows])
        pivots, reps, r = summarise(ords, grps, X, L1, self.k)
        for role, found in (("pivot", list(enumerate(pivots))), ("rep", reps)):
            for p, i in found:
                yield int(self.rows[0][0]), role, int(p), int(ords[i]), float(r)


def register(spark: SparkSession) -> None:
    """Make the functions known to a session's SQL."""
    for name, (kind, gives, text) in DISTANCES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a {kind}, b {kind}) RETURNS {gives} RETURN {text}")
    spark.udtf.register("fair_block_message", udtf(BlockMessage, returnType="block bigint, role string, pivot bigint, ord bigint, r double"))
