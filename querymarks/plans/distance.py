"""Canonicalized edit distance: weighted distances of the components of two trees."""

from __future__ import annotations

import itertools
import math
from collections import Counter, defaultdict
from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any

import numpy as np

from . import ir
from .canon import _swap, text
from .ir import Derived, Full, Group, Left, Same
from .resolve import table_of

COMPONENTS = ("projection", "distinct", "relation", "join_type", "predicate", "subquery", "aggregate", "group_by", "having", "order_by", "set_op", "limit")
#: Pairings of instances that are all tried.
FEW_PAIRINGS = 720


@dataclass(frozen=True)
class Weights:
    """The instructor's weight of each component; 1 where none is given. granularity: component or node."""

    by: tuple[tuple[str, float], ...] = ()
    granularity: str = "component"

    def of(self, component: str) -> float:
        return dict(self.by).get(component, 1.0)


@dataclass
class Parts:
    """A block taken apart. Conditions come with the place that they stand in: the block, or an outer join's."""

    block: Any
    exists: bool = False
    projection: list[Any] = field(default_factory=list)
    aggregate: list[Any] = field(default_factory=list)
    relation: list[str] = field(default_factory=list)
    derived: list[Derived] = field(default_factory=list)
    outer: list[str] = field(default_factory=list)
    predicate: list[tuple[str, Any]] = field(default_factory=list)
    classes: list[tuple[str, Same]] = field(default_factory=list)
    subquery: list[tuple[str, ir.Exists]] = field(default_factory=list)


def place_of(x: Any) -> str:
    """An outer join, named by the instances of its nullable side."""
    return ("left " if isinstance(x, Left) else "full ") + ",".join(sorted(ir.aliases(x.right)))


def take_apart(q: ir.Select, exists: bool = False) -> Parts:
    out = Parts(q, exists)
    if not exists:
        for x in q.items:
            (out.aggregate if ir.has_aggregate(x.expr) else out.projection).append(x.expr)
    for e in (*(q.having or ()), *(k.expr for k in q.order)):
        out.aggregate += [x for x in ir.walk(e) if isinstance(x, ir.Agg)] if not isinstance(e, ir.Exists) else []

    def conditions(place: str, preds: tuple) -> None:
        for p in preds:
            if isinstance(p, ir.Exists):
                out.subquery.append((place, p))
            elif isinstance(p, Same):
                out.classes.append((place, p))
            else:
                out.predicate.append((place, p))

    def group(g: Group, place: str) -> None:
        for x in g.items:
            if isinstance(x, Derived):
                out.derived.append(x)
            elif isinstance(x, ir.Table):
                out.relation.append(x.alias)
            elif isinstance(x, (Left, Full)):
                name = place_of(x)
                out.outer.append(name)
                group(x.left, f"{name}/kept")
                group(x.right, f"{name}/null")
                conditions(name, x.on)
        conditions(place, g.preds)

    group(q.frm, "")
    return out


def _cost(p: Any, weights: Weights) -> float:
    return 1.0 if weights.granularity == "component" else float(query_size(p))


def query_size(node: Any, connectives: bool = True) -> int:
    """Nodes of the flattened tree: attributes, relations, comparisons and operands; DISTINCT, connectives and set
    operators count with ``connectives``."""
    if isinstance(node, ir.SetOp):
        return sum(query_size(p, connectives) for p in node.parts) + connectives * (len(node.parts) - 1)
    if isinstance(node, ir.Select):
        parts = [*(x.expr for x in node.items), *node.group, *(node.having or ()), *(k.expr for k in node.order)]
        return sum(query_size(p, connectives) for p in parts) + query_size(node.frm, connectives) + connectives * node.distinct + (node.limit is not None)
    if isinstance(node, Group):
        return sum(query_size(x, connectives) for x in (*node.items, *node.preds))
    if isinstance(node, (Left, Full)):
        return query_size(node.left, connectives) + query_size(node.right, connectives) + sum(query_size(p, connectives) for p in node.on) + connectives
    if isinstance(node, ir.Exists):
        inner = node.query
        inside = query_size(inner, connectives)
        return inside - (len(inner.items) if isinstance(inner, ir.Select) else 0) + connectives
    if isinstance(node, Derived):
        return query_size(node.query, connectives)
    if isinstance(node, Same):
        return 3 * (len(node.members) - 1)
    if isinstance(node, (ir.Cmp, ir.Like)):
        sides = (node.left, node.right) if isinstance(node, ir.Cmp) else (node.arg, node.pattern)
        return 1 + sum(query_size(x, connectives) for x in sides)
    if isinstance(node, (ir.And, ir.Or)):
        return 1 + sum(query_size(x, connectives) for x in node.args)
    if isinstance(node, (ir.IsNull, ir.Not)):
        return 1 + query_size(node.arg, connectives)
    if isinstance(node, ir.Scalar):
        return query_size(node.query, connectives)
    return 1


def block_counts(q: Any, weights: Weights, exists: bool = False) -> Counter:
    """Elements of each component, subqueries summed: what a whole tree is worth."""
    out: Counter = Counter()
    if isinstance(q, ir.SetOp):
        out["set_op"] += len(q.parts) - 1
        for p in q.parts:
            out.update(block_counts(p, weights))
        out["order_by"] += len(q.order)
        out["limit"] += q.limit is not None
        return out
    p = take_apart(q, exists)
    out.update(projection=len(p.projection), aggregate=len(p.aggregate), relation=len(p.relation), join_type=len(p.outer), distinct=int(q.distinct), group_by=len(q.group), having=len(q.having or ()), order_by=len(q.order), limit=int(q.limit is not None) + int(q.offset is not None))
    for _, x in p.predicate:
        out["predicate"] += _cost(x, weights)
    for _, x in p.classes:
        out["predicate"] += (len(x.members) - 1) * (1.0 if weights.granularity == "component" else 3.0)
    for _, x in p.subquery:
        out["subquery"] += 1
        out.update(block_counts(x.query, weights, True))
    for d in p.derived:
        out["relation"] += 1
        out.update(block_counts(d.query, weights))
    return out


def total_marks(q: Any, weights: Weights = Weights()) -> float:
    return float(sum(weights.of(k) * n for k, n in block_counts(q, weights).items()))


def assignment(costs: list[list[float]]) -> float:
    """The least sum of costs of a one-to-one matching of rows and columns, by shortest augmenting paths."""
    n = len(costs)
    if not n:
        return 0.0
    c = np.array(costs)
    u, v, match = np.zeros(n + 1), np.zeros(n + 1), np.zeros(n + 1, int)
    for i in range(1, n + 1):
        match[0], j0 = i, 0
        least, back, used = np.full(n + 1, np.inf), np.zeros(n + 1, int), np.zeros(n + 1, bool)
        while True:
            used[j0] = True
            i0, delta, j1 = match[j0], np.inf, 0
            for j in range(1, n + 1):
                if not used[j]:
                    cost = c[i0 - 1][j - 1] - u[i0] - v[j]
                    if cost < least[j]:
                        least[j], back[j] = cost, j0
                    if least[j] < delta:
                        delta, j1 = least[j], j
            u[match[used]] += delta
            v[used] -= delta
            least[~used] -= delta
            j0 = j1
            if not match[j0]:
                break
        while j0:
            match[j0] = match[back[j0]]
            j0 = back[j0]
    return float(sum(c[match[j] - 1][j - 1] for j in range(1, n + 1)))


def bag_distance(a: list[str], b: list[str]) -> int:
    x, y = Counter(a), Counter(b)
    return max(sum((y - x).values()), sum((x - y).values()))


def sequence_distance(a: list[str], b: list[str]) -> int:
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def match_costs(a: list[Any], b: list[Any], pair: Any, alone_a: Any, alone_b: Any) -> float:
    """Least cost of matching two bags, where elements may stay alone."""
    n, m = len(a), len(b)
    big = [[0.0] * (n + m) for _ in range(n + m)]
    for i in range(n + m):
        for j in range(n + m):
            if i < n and j < m:
                big[i][j] = min(pair(a[i], b[j]), 1e6)
            elif i < n:
                big[i][j] = alone_a(a[i])
            elif j < m:
                big[i][j] = alone_b(b[j])
    return assignment(big)


def _both(a: Any, b: Any, w: Weights, exists: bool) -> dict[str, float]:
    """Distance of each component of two trees with fixed labels, unweighted."""
    out: dict[str, float] = defaultdict(float)
    if isinstance(a, ir.SetOp) != isinstance(b, ir.SetOp):
        worth = [sum(block_counts(x, w, exists).values()) for x in (a, b)]
        out["set_op"] += max(worth)
        return out
    if isinstance(a, ir.SetOp):
        out["set_op"] += (a.kind != b.kind or a.every != b.every) + abs(len(a.parts) - len(b.parts))
        out["order_by"] += sequence_distance([text(k) for k in a.order], [text(k) for k in b.order])
        out["limit"] += text_or(a.limit) != text_or(b.limit)
        if "except" in (a.kind, b.kind):
            pairs = list(itertools.zip_longest(a.parts, b.parts))
            for x, y in pairs:
                for k, v in (_both(x, y, w, False) if x is not None and y is not None else block_counts(x if x is not None else y, w)).items():
                    out[k] += v
        else:
            out["set_op"] += match_costs(list(a.parts), list(b.parts), lambda x, y: sum(_both(x, y, w, False).values()), lambda x: sum(block_counts(x, w).values()), lambda x: sum(block_counts(x, w).values()))
        return out
    p, q = take_apart(a, exists), take_apart(b, exists)
    out["projection"] += bag_distance([text(x) for x in p.projection], [text(x) for x in q.projection])
    out["aggregate"] += bag_distance([text(x) for x in p.aggregate], [text(x) for x in q.aggregate])
    out["relation"] += bag_distance([table_of(x) for x in p.relation], [table_of(x) for x in q.relation])
    out["join_type"] += bag_distance(p.outer, q.outer)
    out["distinct"] += a.distinct != b.distinct
    out["group_by"] += bag_distance([text(x) for x in a.group], [text(x) for x in b.group])
    out["having"] += bag_distance([text(x) for x in a.having or ()], [text(x) for x in b.having or ()])
    out["order_by"] += sequence_distance([text(k) for k in a.order], [text(k) for k in b.order])
    out["limit"] += (text_or(a.limit) != text_or(b.limit)) + (text_or(a.offset) != text_or(b.offset))
    shown = lambda xs: [(f"{place}: {text(x)}", x) for place, x in xs]
    if w.granularity == "component":
        out["predicate"] += bag_distance([s for s, _ in shown(p.predicate)], [s for s, _ in shown(q.predicate)])
    else:
        out["predicate"] += match_costs(shown(p.predicate), shown(q.predicate), lambda x, y: 0.0 if x[0] == y[0] else _node_replace(x[1], y[1]), lambda x: _cost(x[1], w), lambda x: _cost(x[1], w))
    unit = 1.0 if w.granularity == "component" else 3.0
    out["predicate"] += match_costs(p.classes, q.classes, lambda x, y: unit * _class_distance(x, y), lambda x: unit * (len(x[1].members) - 1), lambda x: unit * (len(x[1].members) - 1))

    def sub(x: tuple, y: tuple) -> float:
        return float((x[1].no != y[1].no) + (x[0] != y[0]) + sum(_both(x[1].query, y[1].query, w, True).values()))

    worth = lambda x: 1 + sum(block_counts(x[1].query, w, True).values())
    out["subquery"] += match_costs(p.subquery, q.subquery, sub, worth, worth)
    whole = lambda x: 1 + sum(block_counts(x.query, w).values())
    out["relation"] += match_costs(p.derived, q.derived, lambda x, y: float(sum(_both(x.query, y.query, w, False).values())), whole, whole)
    return out


def text_or(x: Any) -> str:
    return "" if x is None else text(x)


def _node_replace(x: Any, y: Any) -> float:
    if isinstance(x, ir.Cmp) and isinstance(y, ir.Cmp):
        return float((x.op != y.op) + sum(0 if text(s) == text(t) else max(query_size(s), query_size(t)) for s, t in ((x.left, y.left), (x.right, y.right))))
    return float(max(query_size(x), query_size(y)))


def _class_distance(x: tuple, y: tuple) -> float:
    a, b = ({text(m) for m in z[1].members} for z in (x, y))
    return max(len(a - b), len(b - a)) + float(x[0] != y[0])


def least_pairing(a: Any, b: Any, cost: Callable[[Any], float]) -> tuple[float, Any]:
    """The least cost, and ``a`` with its instances named as those of ``b`` that they pair with then. Instances of one
    table pair in all orders; where these are more than FEW_PAIRINGS, two of them change places as long as that helps,
    from the order of the canonical labels on (an upper bound then)."""
    own, other = defaultdict(list), defaultdict(list)
    for names, tree in ((own, a), (other, b)):
        for x in ir.walk(tree):
            if isinstance(x, ir.RELATIONS) and x.alias not in names[x.alias.rsplit("_", 1)[0]]:
                names[x.alias.rsplit("_", 1)[0]].append(x.alias)
    pools = {stem: (mine, sorted(set(mine) | set(other.get(stem, ())))) for stem, mine in own.items()}
    pools = {stem: x for stem, x in pools.items() if len(x[1]) > 1}

    def tried(mapping: dict[str, str]) -> tuple[float, Any]:
        tree = _swap(a, mapping) if mapping else a
        return cost(tree), tree

    if math.prod(math.perm(len(pool), len(mine)) for mine, pool in pools.values()) <= FEW_PAIRINGS:
        best = None
        for combo in itertools.product(*([dict(zip(mine, p)) for p in itertools.permutations(pool, len(mine))] for mine, pool in pools.values())):
            got = tried({k: v for c in combo for k, v in c.items()})
            if best is None or got[0] < best[0]:
                best = got
            if not best[0]:
                break
        return best
    orders = {stem: list(pool) for stem, (_, pool) in pools.items()}
    mapped = lambda: {m: x for stem, (mine, _) in pools.items() for m, x in zip(mine, orders[stem])}
    best, better = tried(mapped()), True
    while better and best[0]:
        better = False
        for stem, order in orders.items():
            for i, j in itertools.combinations(range(len(order)), 2):
                if i < len(pools[stem][0]):
                    order[i], order[j] = order[j], order[i]
                    got = tried(mapped())
                    if got[0] < best[0]:
                        best, better = got, True
                    else:
                        order[i], order[j] = order[j], order[i]
    return best


def components(a: Any, b: Any, w: Weights = Weights()) -> dict[str, float]:
    """The distance of each component, with the instances of one table paired at least weighted cost."""
    _, tree = least_pairing(a, b, lambda t: sum(w.of(k) * v for k, v in _both(t, b, w, False).items()))
    got = _both(tree, b, w, False)
    return {k: float(got.get(k, 0.0)) for k in COMPONENTS}


def edit_distance(a: Any, b: Any, w: Weights = Weights()) -> float:
    return sum(w.of(k) * v for k, v in components(a, b, w).items())


def marks_by_distance(a: Any, b: Any, w: Weights = Weights()) -> float:
    """The baseline: what is left of the correct tree's worth after the distance, as a share."""
    total = total_marks(b, w)
    return max(0.0, total - edit_distance(a, b, w)) / total if total else 0.0
