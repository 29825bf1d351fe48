"""Registered queries: callables of (spark, sf_dir) and, where SQL can say the same, DuckDB SQL."""

import re

from polyedge.queries import baselines, methods, panels, relational, surface, workloads


def positive_zero(sql: str) -> str:
    """Add 0.0 to every rounded output: DuckDB rounds small negative numbers to -0.0, Spark to 0.0."""
    out, at = [], 0
    for m in re.finditer(r"\bround\(", sql):
        depth, end = 1, m.end()
        while depth:
            depth += {"(": 1, ")": -1}.get(sql[end], 0)
            end += 1
        if re.match(r" AS (?!BIGINT)[a-z_]", sql[end:]) and end > at:
            out += [sql[at:end], " + 0.0"]
            at = end
    return "".join([*out, sql[at:]])


MODULES = (panels, relational, methods, baselines, surface, workloads)
QUERIES = {k: v for m in MODULES for k, v in m.QUERIES.items()}
ORACLES = {k: positive_zero(v) for m in MODULES for k, v in m.ORACLES.items()}
