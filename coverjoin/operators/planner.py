"""One entry for all methods."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import DataFrame

from ..plans import bounds
from ..plans.model import FD, JoinQuery
from . import allbutone, anchored, baselines, cycles, fd, grid


class TooLarge(ValueError):
    """The bound on the output is above the limit that the caller set."""


#: Rows that a cell of the grid may get on average, for it to be chosen.
CELL_ROWS = 200_000


def choose(q: JoinQuery, fds: Sequence[FD] | None = None) -> str:
    """The most special method with a guarantee that fits the query's shape."""
    h = q.hypergraph
    if fds:
        return "fd"
    if h.n == 3 and h.is_all_but_one():
        return "triangle"
    if h.is_all_but_one():
        return "allbutone"
    if h.cycle():
        return "cycle"
    return "graph" if h.is_graph() else "anchored"


def weigh(q: JoinQuery, cells: int = 64) -> dict[str, float]:
    """Rows that each way makes, as far as sizes tell. pairwise: for three relations the least of the exact degree sums, else the
    dynamic program's estimate; bound: what the methods with a guarantee keep to; grid: rows its one shuffle moves, if a cell can hold
    its part, else infinity."""
    sizes = q.sizes()
    pairwise = float(min(allbutone.split_costs(q).values())) if q.hypergraph.n == 3 and q.hypergraph.is_all_but_one() else baselines.dp_plan(q)[1]
    sent = grid.replication(q, grid.shares(q, cells))
    return {"pairwise": pairwise, "bound": bounds.cover_bound(q.hypergraph, sizes), "grid": float(sent) if sent <= cells * CELL_ROWS else math.inf}


def join(q: JoinQuery, strategy: str = "auto", fds: Sequence[FD] | None = None, max_output_rows: int | None = None, **how) -> DataFrame:
    """Natural join. strategy: auto, triangle, allbutone, anchored, cycle, graph, fd, grid, pairwise, catalyst, join_project.

    max_output_rows refuses queries whose bound (known from sizes alone, before any join) is above it. "auto" takes the method for the
    query's shape. A triangle is split at the attribute of the least degree sum, and where that sum is within the bound, no key can be
    worth deferring: the pairwise plan from that attribute is run. A query without a special shape goes pairwise if the estimated
    intermediates stay within the bound, to the grid if its one shuffle moves fewer rows than the bound and cells can hold their parts,
    else to the general method.
    """
    if max_output_rows is not None and bounds.cover_bound(q.hypergraph, q.sizes()) > max_output_rows:
        raise TooLarge(f"up to {bounds.floor_bound(q.hypergraph, q.sizes())} rows")
    if strategy == "auto":
        strategy = choose(q, fds)
        if strategy == "triangle" and not how:
            if 0 in q.sizes():
                return q.empty()
            costs = allbutone.split_costs(q)
            at = min(costs, key=lambda a: (costs[a], a))
            if costs[at] <= bounds.cover_bound(q.hypergraph, q.sizes()):
                first = [i for i, r in enumerate(q.relations) if at in r.attrs]
                return baselines.left_deep(q, [*first, *(i for i in range(3) if i not in first)])
            how = {"split": at}
        elif strategy == "anchored" and not how and 0 not in q.sizes():
            cost = weigh(q)
            if cost["pairwise"] <= cost["bound"]:
                strategy = "pairwise"
            elif cost["grid"] <= cost["bound"]:
                strategy = "grid"
    run = {
        "triangle": allbutone.triangle, "allbutone": allbutone.join, "anchored": anchored.join, "cycle": cycles.cycle, "graph": cycles.graph_join, "grid": grid.join,
        "pairwise": lambda q: baselines.dp_order(q), "catalyst": baselines.catalyst_sql, "join_project": baselines.join_project, "fd": lambda q, **k: fd.join(q, fds, **k),
    }
    return run[strategy](q, **how)


def bound_report(q: JoinQuery) -> dict[str, float]:
    """What is known before running: trivial bounds, the cover bound, and the number of rows of each relation."""
    sizes = q.sizes()
    return {"product": float(math.prod(sizes)), "integral": float(bounds.integral_cover_bound(q.hypergraph, sizes)), "cover": float(bounds.floor_bound(q.hypergraph, sizes))}
