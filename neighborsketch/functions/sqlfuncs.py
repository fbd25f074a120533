"""Functions for SQL users; ``register`` adds them to a session."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .params import PRIME

#: Name and body of each SQL function.
BODIES = {
    "jaccard(a ARRAY<BIGINT>, b ARRAY<BIGINT>) RETURNS DOUBLE": "try_divide(size(array_intersect(a, b)), size(array_union(a, b)))",
    "element_code(x STRING) RETURNS BIGINT": f"CAST(conv(substr(md5(x), 1, 8), 16, 10) AS BIGINT) % {PRIME}",
    "minhash_code(elements ARRAY<BIGINT>, alpha BIGINT, beta BIGINT) RETURNS BIGINT": f"array_min(transform(elements, e -> (alpha * e + beta) % {PRIME}))",
    "median_of(xs ARRAY<DOUBLE>) RETURNS DOUBLE": "(element_at(array_sort(xs), CAST(floor((size(xs) + 1) / 2) AS INT)) + element_at(array_sort(xs), CAST(floor((size(xs) + 2) / 2) AS INT))) / 2",
}


@udtf(returnType="shingle string, position int")
class Shingles:
    """``shingles(text, k)``: all runs of k tokens."""

    def eval(self, text: str, k: int):
        tokens = (text or "").split()
        if tokens and len(tokens) < k:
            yield " ".join(tokens), 0
        for i in range(len(tokens) - k + 1):
            yield " ".join(tokens[i : i + k]), i


@udtf(returnType="id bigint")
class IdsInColumn:
    """``ids_in_column(a, b, cols, col, n)``: the ids below n that a row of the grid puts
    into a column, by inverting its hash instead of scanning all ids."""

    def eval(self, a: int, b: int, cols: int, col: int, n: int):
        inverse = pow(a, -1, PRIME)
        for h in range(col, PRIME, cols) if n > PRIME // 4 else ():
            i = (h - b) * inverse % PRIME
            if i < n:
                yield (i,)
        for first in range(0, n, 1 << 20) if n <= PRIME // 4 else ():
            i = np.arange(first, min(n, first + (1 << 20)))
            for found in i[(a * i + b) % PRIME % cols == col].tolist():
                yield (found,)


def register(spark: SparkSession) -> list[str]:
    for head, body in BODIES.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("shingles", Shingles)
    spark.udtf.register("ids_in_column", IdsInColumn)
    return [h.split("(")[0] for h in BODIES] + ["shingles", "ids_in_column"]
