"""Runs a plan: jobs side by side on their allotments, outputs merged as soon as two are done."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

from pyspark.sql import DataFrame

from ..plan.planner import Plan, name_of
from ..query import MultiJoinQuery, RelOp
from ..sources import materialise
from .merge import merge_outputs, shared_ids
from .single_job import co_partitioned, equality_spans, relations_of, run_trail


class Units:
    """As many units as there are; jobs get their shares in the order of their tickets, so that no small one overtakes a planned one."""

    def __init__(self, total: int):
        self.free, self.total, self.turn, self.next = total, total, threading.Condition(), 0

    def take(self, n: int, ticket: int | None = None) -> None:
        with self.turn:
            self.turn.wait_for(lambda: self.free >= min(n, self.total) and (ticket is None or ticket == self.next))
            self.free -= min(n, self.total)
            if ticket is not None:
                self.next += 1
                self.turn.notify_all()

    def give(self, n: int) -> None:
        with self.turn:
            self.free += min(n, self.total)
            self.turn.notify_all()


@dataclass
class Run:
    ids: DataFrame
    history: list[dict] = field(default_factory=list)


def run_plan(q: MultiJoinQuery, plan: Plan, units: int, seed: int = 0, curve: str = "auto", finish: Callable[[DataFrame], DataFrame] | None = None) -> Run:
    """Row ids of the answer. Every job's output is written (a restart point) before it is merged.

    The last merge is left to whoever reads the ids, and so is the only job of a plan where its plan needs no setting.
    finish is applied to the ids before anything of the last step is written: what it sums up is all that is written.
    """
    spark = next(iter(q.relations.values())).sparkSession
    share = {p.name: (p.start, p.units) for p in plan.schedule.placed}
    cards = lambda labels: [plan.rows[a] for a in relations_of(q, labels)] if plan.rows else None
    trail = lambda labels, n: run_trail(q, labels, n, method=plan.methods.get(name_of(labels), "auto"), curve=curve, seed=seed, cards=cards(labels))
    if len(plan.jobs) == 1:
        labels = plan.jobs[0].labels
        n = plan.schedule.placed[0].units
        note = {"job": name_of(labels), "labels": sorted(labels), "reducers": n, "predicted": plan.jobs[0].weight, "started": 0.0, "seconds": 0.0}
        if finish:
            with co_partitioned(spark):
                return Run(materialise(finish(trail(labels, n)), "finished"), [note])
        hashed = plan.methods.get(name_of(labels), "hash" if equality_spans(q, labels) else "cube") == "hash"
        if hashed or all(p.op is not RelOp.EQ for p in q.predicates if p.label in labels):
            return Run(trail(labels, n), [note])
    pool, history, began, merges_left = Units(units), [], time.time(), [len(plan.jobs) - 1]
    done: list[DataFrame] = []
    lock = threading.Lock()

    def work(ticket, c):
        name = name_of(c.labels)
        n = share[name][1]
        pool.take(n, ticket)
        t = time.time()
        try:
            out = materialise(trail(c.labels, n), f"job-{name}")
        finally:
            pool.give(n)
        history.append({"job": name, "labels": sorted(c.labels), "reducers": n, "predicted": c.weight, "started": t - began, "seconds": time.time() - t})
        merge(out)

    def merge(out):
        # Takes a finished output that shares a relation, or leaves this one for a later job.
        while True:
            with lock:
                other = next((o for o in done if shared_ids(o, out)), None)
                if other is None:
                    done.append(out)
                    return
                done[:] = [o for o in done if o is not other]
                merges_left[0] -= 1
                if not merges_left[0]:
                    done.append(merge_outputs([other, out]))
                    return
            t = time.time()
            out = materialise(merge_outputs([other, out]), "merged")
            history.append({"job": "merge", "labels": [], "reducers": 0, "predicted": 0.0, "started": t - began, "seconds": time.time() - t})

    with co_partitioned(spark), ThreadPoolExecutor(max(1, len(plan.jobs))) as threads:
        # jobs of one start: the larger share first, as the schedule places them
        planned = sorted(plan.jobs, key=lambda c: (share[name_of(c.labels)][0], -share[name_of(c.labels)][1]))
        for f in [threads.submit(work, ticket, c) for ticket, c in enumerate(planned)]:
            f.result()
    ids = done[0] if len(done) == 1 else merge_outputs(done)
    return Run(materialise(finish(ids), "finished") if finish else ids, history)
