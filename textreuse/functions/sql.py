"""Functions for SQL users: pure expressions that Catalyst inlines, and a table function for ad-hoc pairs."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="a_begin int, a_end int, b_begin int, b_end int, n_seeds int")
class ReuseCases:
    """Cases between two texts: equal word n-grams, merged by islands along a and then b, twice."""

    def eval(self, a: str, b: str, n: int, k: int, delta: int):
        if a is None or b is None:
            return

        def grams(text: str):
            ws = re.sub(r"[^\W\d_]+|.", lambda m: m[0] if m[0].isalpha() else " ", text.lower(), flags=re.DOTALL).split()
            at, out = 0, []
            starts = []
            for w in ws:
                starts.append(at)
                at += len(w) + 1
            for p in range(0, len(ws) - n + 1, n - k):
                out.append((" ".join(ws[p : p + n]), starts[p], starts[p + n - 1] + len(ws[p + n - 1])))
            return out

        where: dict = {}
        for g, s, e in grams(b):
            where.setdefault(g, []).append((s, e))
        groups = [[(s, e, x, y) for g, s, e in grams(a) for x, y in where.get(g, ())]]
        for i in (0, 2, 0, 2):
            split = []
            for group in groups:
                far = None
                for row in sorted(group, key=lambda r: r[i : i + 2]):
                    if far is None or row[i] - far > delta:
                        split.append([])
                    split[-1].append(row)
                    far = row[i + 1] if far is None or row[i] - far > delta else max(far, row[i + 1])
            groups = split
        for group in groups:
            if group:
                s, e, x, y = zip(*group, strict=True)
                yield min(s), max(e), min(x), max(y), len(group)


def register(spark: SparkSession) -> None:
    """Temporary functions of the session: ``clean_text``, ``f_beta``, ``min_shared_words``, and the table function ``reuse_cases``."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION clean_text(s STRING) RETURNS STRING RETURN trim(regexp_replace(lower(coalesce(s, '')), '[^\\\\p{L}]+', ' '))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION f_beta(p DOUBLE, r DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN CASE WHEN p + r > 0 THEN (1 + b * b) * p * r / (b * b * p + r) ELSE 0D END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION min_shared_words(n INT, m INT) RETURNS BIGINT RETURN ceil(2D * n / (m + 1))")
    spark.udtf.register("reuse_cases", ReuseCases)
