"""Memory of a single-machine compiler that materialises all messages, and shuffles of a plan."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def msg_bytes(n: int, k: int, v: int, groups: int = 0) -> int:
    """Resident bytes of N words, K topics, V outcomes: K-vectors for the messages of z and x in both directions and the
    responsibilities of every word, two a group, and one V-vector of parameters and one of expected logs a component.

    It does not explain the published 512 GB, which would need copies of the components' vectors a word."""
    return 8 * (4 * n * k + n * k + 2 * groups * k + 2 * v * k)


def exchanges(df: DataFrame, above: str = "InMemoryTableScan") -> int:
    """Shuffles of the physical plan that aren't below a cached table."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    depth, count = None, 0
    for line in plan.splitlines():
        at = len(line) - len(line.lstrip(" +-:*|"))
        if depth is not None and at > depth:
            continue
        depth = at if above in line else None
        count += bool(re.search(r"\bExchange\b", line))
    return count
