"""The rules from SQL text: table functions and scalar functions to register in a session."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from supportbounds.operators.rules import template_rows


class DeductionRules:
    """deduction_rules(n, max_depth): the terms of all rules of an n-set."""

    def eval(self, n: int, max_depth: int):
        yield from template_rows(n, max_depth)


class Powerset:
    """powerset(items): all subsets of an array, the empty one too."""

    def eval(self, items: list):
        held = sorted(set(items))
        for mask in range(1 << len(held)):
            yield ([x for i, x in enumerate(held) if mask >> i & 1],)


def _interval(supports: list[int]) -> tuple[int, int]:
    """Bounds from the supports of all proper subsets in mask order (2^n - 1 of them)."""
    size = len(supports) + 1
    n = size.bit_length() - 1
    g = [*supports, 0]
    for bit in range(n):
        for mask in range(size):
            if not mask >> bit & 1:
                g[mask] -= g[mask | 1 << bit]
    depth = [n - m.bit_count() for m in range(size)]
    return max(-g[m] for m in range(size) if depth[m] % 2 == 0), min(g[m] for m in range(size) if depth[m] % 2)


def register(spark: SparkSession) -> None:
    """deduction_rules, powerset (tables); itemset_subsets, itemset_bounds (scalars)."""
    spark.udtf.register("deduction_rules", F.udtf(DeductionRules, returnType="n int, base_mask bigint, term_mask bigint, sign int, depth int"))
    spark.udtf.register("powerset", F.udtf(Powerset, returnType="items array<string>"))

    @F.pandas_udf("struct<lower:bigint,upper:bigint>")
    def itemset_bounds(supports: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([_interval(list(map(int, s))) for s in supports], columns=["lower", "upper"])

    @F.pandas_udf("array<array<string>>")
    def itemset_subsets(items: pd.Series, k: pd.Series) -> pd.Series:
        from itertools import combinations

        return pd.Series([[list(c) for c in combinations(sorted(set(i)), int(n))] for i, n in zip(items, k, strict=True)])

    spark.udf.register("itemset_bounds", itemset_bounds)
    spark.udf.register("itemset_subsets", itemset_subsets)
