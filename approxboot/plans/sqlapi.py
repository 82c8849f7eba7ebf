"""Early answers from SQL: SELECT of one aggregate block, answered from a sample."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from approxboot.functions import statistics as st
from approxboot.functions.rng import poisson_cdf
from approxboot.plans.driver import fixed_plan

_FUNCTIONS = {"avg": st.mean, "mean": st.mean, "sum": st.total, "median": st.quantile, "variance": st.variance, "var_pop": st.variance, "count": st.count}


def parse_block(sql: str) -> tuple[list[str], list[tuple[str, str, str]], str]:
    """(group columns, [(function, argument, alias)], from-clause) of one aggregate block; anything else is refused."""
    m = re.fullmatch(r"(?is)\s*select\s+(.+?)\s+from\s+(.+?)(?:\s+group\s+by\s+(.+?))?\s*;?\s*", sql)
    if not m or re.search(r"(?i)\b(having|order\s+by|limit|union|distinct)\b", sql):
        raise ValueError("one SELECT of aggregates with FROM, WHERE and GROUP BY is accepted")
    groups = [g.strip() for g in (m[3] or "").split(",") if g.strip()]
    calls, depth, item, items = [], 0, "", []
    for ch in m[1] + ",":
        depth += (ch == "(") - (ch == ")")
        if ch == "," and not depth:
            items.append(item.strip())
            item = ""
        else:
            item += ch
    for it in items:
        call = re.fullmatch(r"(?is)(\w+)\s*\((.*)\)\s*(?:as\s+)?(\w+)?", it)
        if call and call[1].lower() in _FUNCTIONS:
            calls.append((call[1].lower(), call[2].strip(), call[3] or f"{call[1].lower()}_{len(calls)}"))
        elif it not in groups:
            raise ValueError(f"not an aggregate that can be answered early: {it}")
    return groups, calls, m[2]


def early_sql(spark: SparkSession, sql: str, ids: list[str], p: float, B: int = 30, seed: int = 0, kind: str = "xx") -> DataFrame:
    """(group columns, aggregate, value, cv, lo, hi, n) of a SELECT, from a sample of fraction p. Spark analyses the FROM and WHERE; joins stay in it."""
    groups, calls, source = parse_block(sql)
    base = spark.sql(f"select * from {source}")
    out = None
    for f, arg, alias in calls:
        stat = st.count() if f == "count" and arg in ("*", "1") else _FUNCTIONS[f](F.expr(arg) if f != "count" else F.expr(f"{arg} is not null"))
        one = fixed_plan(base, stat, ids, p, B, groups, seed=seed, kind=kind).select(*groups, F.lit(alias).alias("aggregate"), "value", "cv", "lo", "hi", "n")
        out = one if out is None else out.unionByName(one)
    return out


@udtf(returnType="b int, id bigint, w int")
class BootstrapRows:
    """TABLE argument with columns id and x, and a number of replicates: (b, id, w) for weights above 0."""

    def eval(self, row, replicates: int):
        import hashlib

        for b in range(replicates):
            u = int(hashlib.md5(f"boot|0|{row['id']}|{b}".encode()).hexdigest()[:12], 16) / (1 << 48)
            w = next((k for k, c in enumerate(poisson_cdf()) if u < c), 8)
            if w:
                yield b, row["id"], w
