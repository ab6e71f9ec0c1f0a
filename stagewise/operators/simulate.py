"""Virtual-clock runs of chains or stages on W workers."""

from __future__ import annotations

import heapq

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from stagewise.plans.schedule import critical_path

_OUT = "policy string, w long, makespan double, busy double, transitions long"


def simulate(
    stages: list[tuple[str, str | None, str, float]], w: int, policy: str, save: float = 0.0, load: float = 0.0, trace: list | None = None
) -> tuple[float, float, int]:
    """stages (id, parent, chain, cost) -> (makespan, busy, transitions).

    ``chains``: an idle worker takes the ready chain of the largest remaining cost and runs it
    whole.  ``breadth``: it takes the ready stage that comes first by level.  A transition is a
    stage whose worker did not run its parent just before; it pays a load, and a stage that is left pays a save.
    ``trace`` is filled with placements (worker, stage, parent, t0, t1).
    """
    cost = {s: c for s, _, _, c in stages}
    parent = {s: p for s, p, _, _ in stages}
    children: dict[str | None, list[str]] = {}
    for s, p, _, _ in stages:
        children.setdefault(p if p in cost else None, []).append(s)
    depth: dict[str, int] = {}
    order, todo = [], [(s, 0) for s in children.get(None, [])]
    while todo:
        s, d = todo.pop()
        depth[s] = d
        order.append(s)
        todo += [(c, d + 1) for c in children.get(s, [])]
    runs: dict[str, list[str]] = {}
    if policy == "chains":
        chain = {s: c for s, _, c, _ in stages}
        for s in sorted(order, key=lambda s: depth[s]):
            runs.setdefault(chain[s], []).append(s)
    else:
        runs = {s: [s] for s in order}
    unit_of = {s: u for u, own in runs.items() for s in own}
    total = {u: sum(cost[s] for s in own) for u, own in runs.items()}
    key = (lambda u: (-total[u], u)) if policy == "chains" else (lambda u: (depth[u], u))
    ready = [(key(u), u) for u, own in runs.items() if parent[own[0]] not in cost]
    heapq.heapify(ready)
    last: dict[int, str | None] = {k: None for k in range(w)}
    running: list[tuple[float, int, str]] = []
    idle = list(range(w))
    now, busy, moves, end = 0.0, 0.0, 0, 0.0
    done_at: list[tuple[float, str]] = []
    while ready or running or done_at:
        while ready and idle:
            _, u = heapq.heappop(ready)
            own = runs[u]
            p = parent[own[0]]
            k = next((x for x in idle if last[x] == p and p is not None), idle[0])
            idle.remove(k)
            at = now
            if p in cost and last[k] != p:
                moves += 1
                at += load
            for n, s in enumerate(own):
                begin, at = now if not n else at, at + cost[s]
                if any(unit_of[c] != u for c in children.get(s, [])):
                    at += save
                if trace is not None:
                    trace.append((k, s, parent[s] if parent[s] in cost else None, begin, at))
                heapq.heappush(done_at, (at, s))
            busy += at - now
            heapq.heappush(running, (at, k, own[-1]))
        now = min([running[0][0]] if running else [], default=now)
        if done_at:
            now = min(now, done_at[0][0])
        while done_at and done_at[0][0] <= now:
            _, s = heapq.heappop(done_at)
            for c in children.get(s, []):
                if unit_of[c] != unit_of[s]:
                    heapq.heappush(ready, (key(unit_of[c]), unit_of[c]))
        while running and running[0][0] <= now:
            t, k, s = heapq.heappop(running)
            last[k] = s
            idle.append(k)
            end = max(end, t)
        idle.sort()
    return end, busy, moves


def run(elected: DataFrame, sweep: list[tuple[str, int]], by: str = "study", save: float = 0.0, load: float = 0.0) -> DataFrame:
    """elected(by, stage, parent, leaf, cost) -> one row per group and (policy, workers).

    A group is one independent cluster; its stages, not its trials, are what a task holds.
    """

    def one(group: pd.DataFrame) -> pd.DataFrame:
        rows = [(s, p if isinstance(p, str) else None, c, float(x)) for s, p, c, x in zip(group["stage"], group["parent"], group["leaf"], group["cost"])]
        out = [(group[by].iloc[0], policy, w, *simulate(rows, w, policy, save, load)) for policy, w in sweep]
        return pd.DataFrame(out, columns=[by, "policy", "w", "makespan", "busy", "transitions"])

    return elected.select(by, "stage", "parent", "leaf", "cost").groupBy(by).applyInPandas(one, f"{by} string, {_OUT}")


def placements(elected: DataFrame, policy: str, w: int, by: str = "study", save: float = 0.0, load: float = 0.0) -> DataFrame:
    """elected(by, stage, parent, leaf, cost) -> (by, worker, stage_id, parent, t0, t1): where and when each stage runs."""

    def one(group: pd.DataFrame) -> pd.DataFrame:
        rows = [(s, p if isinstance(p, str) else None, c, float(x)) for s, p, c, x in zip(group["stage"], group["parent"], group["leaf"], group["cost"])]
        trace: list = []
        simulate(rows, w, policy, save, load, trace)
        return pd.DataFrame([(group[by].iloc[0], *x) for x in trace], columns=[by, "worker", "stage_id", "parent", "t0", "t1"])

    return elected.select(by, "stage", "parent", "leaf", "cost").groupBy(by).applyInPandas(one, f"{by} string, worker long, stage_id string, parent string, t0 double, t1 double")


def bounds(stages: DataFrame, lines: DataFrame, w: int) -> DataFrame:
    """(w, work, path, least): no run on ``w`` workers ends before the critical path or the work over the workers; for clusters too large to simulate."""
    work = stages.agg(F.sum("cost").alias("work"))
    both = work.crossJoin(F.broadcast(critical_path(stages, lines).select(F.col("total").alias("path"))))  # one row each
    return both.select(F.lit(w).cast("long").alias("w"), "work", "path", F.greatest(F.col("work") / w, F.col("path")).alias("least"))
