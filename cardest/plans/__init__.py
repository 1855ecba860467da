"""Candidate plans, their costs from estimates, and the choice."""

from __future__ import annotations

import itertools
import math
import time
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cardest.estimators import exact, sample
from cardest.query.compile import to_dataframe
from cardest.query.ir import Query
from cardest.sampling.build import SampleDB

#: Rows below which a side is asked to be broadcast.
BROADCAST_ROWS = 100_000
#: Index-matched hits below which a join's estimate is better taken from its edges.
FEW_HITS = 30


@dataclass(frozen=True)
class PlanNode:
    """Binary tree of joins over aliases; selections stand at the leaves."""

    aliases: frozenset[str]
    left: PlanNode | None = None
    right: PlanNode | None = None

    @property
    def joins(self) -> list[frozenset[str]]:
        return [] if self.left is None else [*self.left.joins, *self.right.joins, self.aliases]

    def text(self) -> str:
        return next(iter(self.aliases)) if self.left is None else f"({self.left.text()} {self.right.text()})"

    def order(self) -> list[str]:
        return list(self.aliases) if self.left is None else [*self.left.order(), *self.right.order()]


def leaf_select_plan(q: Query, order: list[str] | None = None) -> PlanNode:
    """The left-deep plan in the given order."""
    out: PlanNode | None = None
    for a in order or list(q.aliases):
        leaf = PlanNode(frozenset([a]))
        out = leaf if out is None else PlanNode(out.aliases | leaf.aliases, out, leaf)
    return out


def subqueries(q: Query, plan: PlanNode) -> dict[str, Query]:
    """The query below every node; all belong to the class of the query."""
    sets = [frozenset([a]) for a in q.aliases] + plan.joins
    return {"+".join(sorted(s)): q.restricted(s) for s in sets}


def connected(q: Query, aliases: frozenset[str]) -> bool:
    seen, todo = set(), [next(iter(aliases))]
    while todo:
        a = todo.pop()
        if a not in seen:
            seen.add(a)
            todo += [x for e in q.joins for x, y in ((e.a1, e.a2), (e.a2, e.a1)) if y == a and x in aliases]
    return seen == set(aliases)


def enumerate_plans(q: Query, shape: str = "left") -> list[PlanNode]:
    """All plans without products, bottom up; sub-plans are shared objects."""
    best: dict[frozenset[str], list[PlanNode]] = {frozenset([a]): [PlanNode(frozenset([a]))] for a in q.aliases}
    for size in range(2, len(q.aliases) + 1):
        for combo in itertools.combinations(sorted(q.aliases), size):
            whole = frozenset(combo)
            if not connected(q, whole):
                continue
            plans = []
            for k in (1,) if shape == "left" else range(1, size // 2 + 1):
                for part in itertools.combinations(combo, k):
                    right = frozenset(part)
                    left = whole - right
                    if left in best and right in best and (shape == "left" or k * 2 < size or min(left) < min(right)):
                        plans += [PlanNode(whole, a, b) for a in best[left] for b in best[right]]
            best[whole] = plans
    return best.get(frozenset(q.aliases), [])


class SubplanMemo:
    """Estimates of sub-queries, each computed once, missing ones of many plans in one batch.

    A join of fewer than ``few_hits`` index-matched hits is estimated anew: its leaves times the cross-sample selectivities
    of its edges, taken for independent. That carries no guarantee, but does not call a key join empty.
    """

    def __init__(self, sdb: SampleDB, few_hits: int = 0) -> None:
        self.sdb, self.known, self.asked, self.few_hits, self.edges = sdb, {}, 0, few_hits, {}

    def cards(self, q: Query, sets) -> dict[frozenset[str], float]:
        todo = {self.key(q, s): s for s in sets if self.key(q, s) not in self.known}
        if todo:
            self.asked += len(todo)
            found = sample.estimate_all({k: q.restricted(s) for k, s in todo.items()}, self.sdb).collect()  # one row a sub-query
            self.known |= {r["query_id"]: r["cardinality"] for r in found}
            weak = [todo[r["query_id"]] for r in found if r["hits"] < self.few_hits and len(todo[r["query_id"]]) > 1]
            for s, card in self.by_edges(q, weak).items():
                self.known[self.key(q, s)] = card
        return {s: self.known[self.key(q, s)] for s in sets}

    def by_edges(self, q: Query, sets: list[frozenset[str]]) -> dict[frozenset[str], float]:
        """Leaf cardinalities of each set times the cross-sample selectivities of its edges; all edges in one job."""
        inside = {s: q.restricted(s).joins for s in sets}
        todo = [e for e in q.joins if any(e in es for es in inside.values()) and e not in self.edges]
        if todo:
            parts = [sample.cross_estimate(Query({e.a1: q.tables[e.a1], e.a2: q.tables[e.a2]}, {}, (e,)), self.sdb).select(F.lit(i).alias("edge"), "sigma") for i, e in enumerate(todo)]
            self.edges |= {todo[r["edge"]]: r["sigma"] for r in reduce(DataFrame.unionByName, parts).collect()}  # one row an edge
        leaves = self.cards(q, {frozenset([a]) for s in sets for a in s}) if sets else {}
        return {s: product([*(leaves[frozenset([a])] for a in s), *(self.edges[e] for e in es)]) for s, es in inside.items()}

    @staticmethod
    def key(q: Query, s: frozenset[str]) -> str:
        return q.restricted(s).key()


def plan_cost(plan: PlanNode, cards: dict[frozenset[str], float]) -> float:
    """Rows of all intermediate results."""
    return sum(cards[s] for s in plan.joins)


def all_sets(plans: list[PlanNode]) -> set[frozenset[str]]:
    return {s for p in plans for s in p.joins} | {frozenset([a]) for p in plans for a in p.aliases}


def choose(q: Query, plans: list[PlanNode], cards: dict[frozenset[str], float]) -> PlanNode:
    return min(plans, key=lambda p: (plan_cost(p, cards), p.text()))


def optimize(q: Query, db: dict[str, DataFrame], sdb: SampleDB, shape: str = "left", few_hits: int = 0) -> tuple[DataFrame, PlanNode]:
    """The query in the order of the cheapest plan; sides that are estimated small are hinted for broadcast.

    ``few_hits`` as in ``SubplanMemo``; ``FEW_HITS`` suits queries with key joins.

    The order is fixed by construction; the session's own join reordering is off unless asked for, and does not undo it.
    """
    plans = enumerate_plans(q, shape)
    cards = SubplanMemo(sdb, few_hits).cards(q, all_sets(plans))
    plan = choose(q, plans, cards)
    hints = {a: "broadcast" for a in q.aliases if sdb.sizes[a] <= BROADCAST_ROWS}  # base rows, exact, are the bound
    return to_dataframe(q, db, plan.order(), hints), plan


def explain_choice(q: Query, sdb: SampleDB, shape: str = "left") -> list[tuple[str, float]]:
    plans = enumerate_plans(q, shape)
    cards = SubplanMemo(sdb).cards(q, all_sets(plans))
    return sorted(((p.text(), plan_cost(p, cards)) for p in plans), key=lambda x: (x[1], x[0]))


def regret(q: Query, plans: list[PlanNode], estimated: dict[frozenset[str], float], true: dict[frozenset[str], float]) -> float:
    """True cost of the plan that the estimates choose over the true cost of the best one."""
    best = plan_cost(choose(q, plans, true), true)
    return plan_cost(choose(q, plans, estimated), true) / best if best else 1.0


def true_cards(q: Query, sets, db: dict[str, DataFrame]) -> dict[frozenset[str], float]:
    named = {"+".join(sorted(s)): s for s in sets}
    rows = exact.exact_all({n: q.restricted(s) for n, s in named.items()}, db).collect()
    return {named[r["query_id"]]: float(r["truth"]) for r in rows}


def time_estimation(q: Query, db: dict[str, DataFrame], sdb: SampleDB) -> dict[str, float]:
    """Seconds to estimate and to execute."""
    t0 = time.perf_counter()
    sample.estimate_all({"q": q}, sdb).collect()
    t1 = time.perf_counter()
    to_dataframe(q, db).write.format("noop").mode("overwrite").save()
    return {"estimate_s": t1 - t0, "execute_s": time.perf_counter() - t1}


def product(sizes) -> float:
    return math.prod(map(float, sizes))
