"""Guided edits: single changes that bring a student's tree nearer to a correct one."""

from __future__ import annotations

from collections import Counter
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Any

from . import ir
from .canon import text
from .distance import Weights, _both, _cost, block_counts, place_of, take_apart
from .ir import Derived, Exists, Full, Group, Item, Left, Select, replace
from .resolve import shape, table_of
from .rules_semantic import free_rels

KINDS = ("replace", "move", "delete", "insert", "convert", "reorder")


@dataclass(frozen=True)
class Edit:
    op: str
    component: str
    path: str
    before: str
    after: str
    cost: float


@dataclass(frozen=True)
class Step:
    tree: Any
    cost: float
    edit: Edit


class Editor:
    """``extended`` adds edits of set operators, LIMIT and HAVING. ``shared``: shapes of conditions that stand in a
    WITH block used several times: one edit, and one cost, for all copies."""

    def __init__(self, weights: Weights = Weights(), extended: bool = False, shared: frozenset = frozenset()):
        self.w, self.extended, self.shared = weights, extended, shared

    def steps(self, a: Any, b: Any) -> list[Step]:
        seen: dict[str, Step] = {}
        for s in self.query(a, b, "", set(), False, True):
            key = text(s.tree)
            if key not in seen or s.cost < seen[key].cost:
                seen[key] = s
        return list(seen.values())

    def step(self, tree: Any, op: str, component: str, path: str, before: Any, after: Any, units: float = 1.0) -> Step:
        cost = self.w.of(component) * units
        show = lambda x: "" if x is None else x if isinstance(x, str) else text(x)
        return Step(tree, cost, Edit(op, component, path, show(before), show(after), cost))

    # -- queries
    def query(self, a: Any, b: Any, path: str, scope: set[str], exists: bool, project: bool) -> Iterator[Step]:
        if isinstance(a, Select) and isinstance(b, Select):
            yield from self.block(a, b, path, scope, exists, project)
        elif isinstance(a, ir.SetOp) and isinstance(b, ir.SetOp):
            yield from self.set_operation(a, b, path, scope)
        elif isinstance(b, ir.SetOp):
            yield from self.part_of(a, b, path, scope)
        else:
            for i, p in enumerate(a.parts):
                cost = 1 + sum(self.worth(x) for x in a.parts) - self.worth(p)
                yield self.step(p, "delete", "set_op", path, f"all but part {i + 1} of {a.kind}", None, cost)

    def part_of(self, a: Select, b: ir.SetOp, path: str, scope: set[str]) -> Iterator[Step]:
        """A block where a set operator should be: it is edited towards the part that it fits, and takes another part
        as a whole once both are of one width."""
        parts = b.parts[:1] if b.kind == "except" else b.parts
        own = min(range(len(parts)), key=lambda j: (sum(_both(a, parts[j], self.w, False).values()), j))
        yield from self.query(a, b.parts[own], path, scope, False, True)
        for j, other in enumerate(b.parts):
            if j != own and len(_outputs(other)) == len(a.items):
                yield self.step(ir.SetOp(b.kind, b.every, (a, other)), "insert", "set_op", path, None, other, 1 + self.worth(other))

    def set_operation(self, a: ir.SetOp, b: ir.SetOp, path: str, scope: set[str]) -> Iterator[Step]:
        if self.extended and (a.kind, a.every) != (b.kind, b.every):
            yield self.step(replace(a, kind=b.kind, every=b.every), "replace", "set_op", path, a.kind + " all" * a.every, b.kind + " all" * b.every)
        if "except" in (a.kind, b.kind):
            pairs = list(zip(range(len(a.parts)), range(len(b.parts))))
        else:
            left, pairs = set(range(len(b.parts))), []
            for i, x in enumerate(a.parts):
                if left:
                    j = min(left, key=lambda j: (sum(_both(x, b.parts[j], self.w, False).values()), j))
                    left.discard(j)
                    pairs.append((i, j))
            if len(a.parts) > len(b.parts) and len(a.parts) > 2:
                for i in set(range(len(a.parts))) - {i for i, _ in pairs}:
                    yield self.step(replace(a, parts=a.parts[:i] + a.parts[i + 1 :]), "delete", "set_op", path, a.parts[i], None, 1 + self.worth(a.parts[i]))
            for j in left:
                yield self.step(replace(a, parts=(*a.parts, b.parts[j])), "insert", "set_op", path, None, b.parts[j], 1 + self.worth(b.parts[j]))
        for i, j in pairs:
            for s in self.query(a.parts[i], b.parts[j], f"{path}/part {i + 1}", scope, False, False):
                yield Step(replace(a, parts=(*a.parts[:i], s.tree, *a.parts[i + 1 :])), s.cost, s.edit)
        # Outputs change in all parts at once, or their widths would differ.
        if len(pairs) == len(a.parts) and all(isinstance(p, Select) for p in (*a.parts, *b.parts)):
            yield from self.joint_projection(a, [b.parts[j] for _, j in sorted(pairs)], path)

    def joint_projection(self, a: ir.SetOp, correct: list[Select], path: str) -> Iterator[Step]:
        wide, want = len(a.parts[0].items), len(correct[0].items)
        column = lambda parts, k: tuple(text(p.items[k].expr) for p in parts)
        mine, theirs = [column(a.parts, k) for k in range(wide)], [column(correct, k) for k in range(want)]
        extra = [k for k in range(wide) if mine[k] not in theirs]
        missing = [k for k in range(want) if theirs[k] not in mine]

        def changed(fn: Callable[[Select, Select], tuple]) -> ir.SetOp:
            return replace(a, parts=tuple(replace(p, items=fn(p, c)) for p, c in zip(a.parts, correct)))

        n = len(a.parts)
        fits = lambda k: all(free_rels(c.items[k].expr) <= ir.aliases(p.frm) for p, c in zip(a.parts, correct))
        for m in missing:
            if not fits(m):
                continue
            if wide < want:
                yield self.step(changed(lambda p, c, m=m: (*p.items[:m], c.items[m], *p.items[m:])), "insert", "projection", path, None, theirs[m][0], n)
            for e in extra:
                differing = sum(x != y for x, y in zip(mine[e], theirs[m]))
                yield self.step(changed(lambda p, c, m=m, e=e: (*p.items[:e], c.items[m], *p.items[e + 1 :])), "replace", "projection", path, mine[e][0], theirs[m][0], differing)
        for e in extra if wide > 1 else ():
            yield self.step(changed(lambda p, c, e=e: p.items[:e] + p.items[e + 1 :]), "delete", "projection", path, mine[e][0], None, n)

    def worth(self, q: Any, exists: bool = False) -> float:
        return float(sum(self.w.of(k) * n for k, n in block_counts(q, self.w, exists).items()))

    # -- one block
    def block(self, a: Select, b: Select, path: str, scope: set[str], exists: bool, project: bool) -> Iterator[Step]:
        visible = scope | ir.aliases(a.frm)
        sees = lambda x: free_rels(x) <= visible
        if not exists and project:
            yield from self.items(a, b, path, sees)
        if a.distinct != b.distinct:
            yield self.step(replace(a, distinct=b.distinct), "insert" if b.distinct else "delete", "distinct", path, None if b.distinct else "DISTINCT", "DISTINCT" if b.distinct else None)
        for field, component in (("group", "group_by"), *((("having", "having"),) if self.extended else ())):
            own, want = tuple(getattr(a, field) or ()), tuple(getattr(b, field) or ())
            for new, op, x, y in self.bag(own, want, sees):
                yield self.step(replace(a, **{field: new}), op, component, path, x, y)
        yield from self.order(a, b, path, sees)
        if self.extended and (a.limit, a.offset) != (b.limit, b.offset):
            yield self.step(replace(a, limit=b.limit, offset=b.offset), "replace", "limit", path, a.limit, b.limit)
        yield from self.conditions(a, b, path, sees)
        yield from self.subqueries(a, b, path, visible)
        yield from self.relations(a, b, path, scope)
        yield from self.join_types(a, b, path)

    def bag(self, own: tuple, want: tuple, sees: Callable) -> Iterator[tuple]:
        extra, missing = _unmatched(own, want), [y for _, y in _unmatched(want, own) if sees(y)]
        for k, x in extra:
            yield own[:k] + own[k + 1 :], "delete", x, None
            for y in missing:
                yield (*own[:k], y, *own[k + 1 :]), "replace", x, y
        for y in missing:
            yield (*own, y), "insert", None, y

    def items(self, a: Select, b: Select, path: str, sees: Callable) -> Iterator[Step]:
        for kind in (False, True):
            own = [(k, x) for k, x in enumerate(a.items) if ir.has_aggregate(x.expr) == kind]
            want = [x for x in b.items if ir.has_aggregate(x.expr) == kind]
            component = "aggregate" if kind else "projection"
            extra = [own[k][0] for k, _ in _unmatched(tuple(x.expr for _, x in own), tuple(x.expr for x in want))]
            missing = [want[k] for k, _ in _unmatched(tuple(x.expr for x in want), tuple(x.expr for _, x in own)) if sees(want[k].expr)]
            for k in extra:
                if len(a.items) > 1:
                    yield self.step(replace(a, items=a.items[:k] + a.items[k + 1 :]), "delete", component, path, a.items[k].expr, None)
                for y in missing:
                    yield self.step(replace(a, items=(*a.items[:k], Item(y.expr, y.name), *a.items[k + 1 :])), "replace", component, path, a.items[k].expr, y.expr)
            for y in missing:
                yield self.step(replace(a, items=(*a.items, Item(y.expr, y.name))), "insert", component, path, None, y.expr)
        # A plain output in the place of an aggregate, or the other way.
        extra = [k for k, _ in _unmatched(tuple(x.expr for x in a.items), tuple(x.expr for x in b.items))]
        missing = [b.items[k] for k, _ in _unmatched(tuple(x.expr for x in b.items), tuple(x.expr for x in a.items)) if sees(b.items[k].expr)]
        for k in extra:
            for y in missing:
                if ir.has_aggregate(y.expr) != ir.has_aggregate(a.items[k].expr):
                    component = "aggregate" if ir.has_aggregate(y.expr) else "projection"
                    yield self.step(replace(a, items=(*a.items[:k], Item(y.expr, y.name), *a.items[k + 1 :])), "replace", component, path, a.items[k].expr, y.expr)

    def order(self, a: Select, b: Select, path: str, sees: Callable) -> Iterator[Step]:
        own, want = a.order, b.order
        if [text(k) for k in own] == [text(k) for k in want]:
            return
        if Counter(map(text, own)) == Counter(map(text, want)):
            for k, x in enumerate(own):  # one key goes to its right place
                rest = own[:k] + own[k + 1 :]
                at = [text(y) for y in want].index(text(x))
                if at != k:
                    yield self.step(replace(a, order=(*rest[:at], x, *rest[at:])), "reorder", "order_by", path, x, f"place {at + 1}")
            return
        for k, x in _unmatched(own, want):
            yield self.step(replace(a, order=own[:k] + own[k + 1 :]), "delete", "order_by", path, x, None)
            for _, y in _unmatched(want, own):
                if sees(y.expr):
                    yield self.step(replace(a, order=(*own[:k], y, *own[k + 1 :])), "replace", "order_by", path, x, y)
        for k, y in _unmatched(want, own):
            if sees(y.expr):
                yield self.step(replace(a, order=(*own[:k], y, *own[k:])), "insert", "order_by", path, None, y)

    # -- conditions
    def conditions(self, a: Select, b: Select, path: str, sees: Callable) -> Iterator[Step]:
        p, q = take_apart(a), take_apart(b)
        mine, theirs = [*p.predicate, *p.classes], [*q.predicate, *q.classes]
        key = lambda x: (x[0], text(x[1]))
        have, want = Counter(map(key, mine)), Counter(map(key, theirs))
        extra = [x for x in dict.fromkeys(mine) if have[key(x)] > want[key(x)]]
        missing = [x for x in dict.fromkeys(theirs) if want[key(x)] > have[key(x)] and sees(x[1])]
        places = {"", *p.outer, *(f"{o}/{side}" for o in p.outer for side in ("kept", "null"))}
        at = lambda place: f"{path} {place}".strip()
        for place, x in extra:
            yield self.everywhere(a, x, None, self.step(edit_place(a, place, x, None), "delete", "predicate", at(place), x, None, _cost(x, self.w)))
            for other, y in missing:
                if other == place:
                    yield self.everywhere(a, x, y, self.step(edit_place(a, place, x, y), "replace", "predicate", at(place), x, y, self.replacing(x, y)))
                elif text(x) == text(y) and other in places:
                    yield self.step(edit_place(edit_place(a, place, x, None), other, None, y), "move", "predicate", at(place), x, other or "WHERE")
        for place, y in missing:
            if place in places:
                yield self.step(edit_place(a, place, None, y), "insert", "predicate", at(place), None, y, _cost(y, self.w))

    def replacing(self, x: Any, y: Any) -> float:
        if self.w.granularity == "component":
            return 1.0
        from .distance import _node_replace

        return max(1.0, _node_replace(x, y))

    def everywhere(self, a: Any, x: Any, y: Any, s: Step) -> Step:
        """Other copies of a condition of a reused WITH block change with it."""
        if shape(x) not in self.shared:
            return s
        rels = sorted(ir.rels(x))

        def one(node: Any) -> Any:
            if not isinstance(node, Group):
                return node
            preds = []
            for p in node.preds:
                if p != x and shape(p) == shape(x) and p != y:
                    names = dict(zip(rels, sorted(ir.rels(p))))
                    if y is None:
                        continue
                    p = ir.rename(y, {k: v for k, v in names.items()})
                preds.append(p)
            return replace(node, preds=tuple(preds))

        return Step(ir.rewrite(s.tree, one), s.cost, s.edit)

    # -- subqueries
    def subqueries(self, a: Select, b: Select, path: str, visible: set[str]) -> Iterator[Step]:
        p, q = take_apart(a), take_apart(b)
        key = lambda x: (x[0], text(x[1]))
        have, want = Counter(map(key, p.subquery)), Counter(map(key, q.subquery))
        extra = [x for x in dict.fromkeys(p.subquery) if have[key(x)] > want[key(x)]]
        missing = [x for x in dict.fromkeys(q.subquery) if want[key(x)] > have[key(x)]]
        for n, (place, x) in enumerate(extra):
            name = f"{path}/{'not ' * x.no}exists {n + 1}"
            yield self.step(edit_place(a, place, x, None), "delete", "subquery", name, x, None, 1 + self.worth(x.query, True))
            for other, y in missing:
                if other != place:
                    continue
                if x.no != y.no:
                    new = Exists(x.query, y.no)
                    yield self.step(edit_place(a, place, x, new), "replace", "subquery", name, "NOT EXISTS" if x.no else "EXISTS", "NOT EXISTS" if y.no else "EXISTS")
                for s in self.query(x.query, y.query, name, visible, True, True):
                    yield Step(edit_place(a, place, x, Exists(s.tree, x.no)), s.cost, s.edit)
        for place, y in missing:
            if free_rels(y) <= visible and len(p.subquery) < len(q.subquery):
                yield self.step(edit_place(a, place, None, y), "insert", "subquery", path, None, y, 1 + self.worth(y.query, True))
        for k, x in enumerate(a.frm.items):
            if isinstance(x, Derived):
                for y in q.derived:
                    if text(x) != text(y):
                        for s in self.query(x.query, y.query, f"{path}/from {x.alias}", visible if x.lateral else set(), False, len(x.columns) == len(y.columns)):
                            if len(_outputs(s.tree)) == len(x.columns):
                                item = replace(x, query=s.tree)
                                yield Step(replace(a, frm=replace(a.frm, items=(*a.frm.items[:k], item, *a.frm.items[k + 1 :]))), s.cost, s.edit)

    # -- relations
    def relations(self, a: Select, b: Select, path: str, scope: set[str]) -> Iterator[Step]:
        mine, theirs = {x.alias: x for x in ir.leaves(a.frm)}, {x.alias: x for x in ir.leaves(b.frm)}
        used = ir.rels(a)
        for alias, x in mine.items():
            if alias not in theirs and alias not in used and len(mine) > 1:
                new = _drop_relation(a.frm, alias)
                if new is not None:
                    worth = 1.0 if isinstance(x, ir.Table) else 1 + self.worth(x.query)
                    yield self.step(replace(a, frm=new), "delete", "relation", path, table_of(alias), None, worth)
        for alias, y in theirs.items():
            if alias not in mine:
                worth = 1.0 if isinstance(y, ir.Table) else 1 + self.worth(y.query)
                yield self.step(replace(a, frm=replace(a.frm, items=(*a.frm.items, y))), "insert", "relation", path, None, table_of(alias), worth)

    def join_types(self, a: Select, b: Select, path: str) -> Iterator[Step]:
        want = {place_of(x): x for x in _outer_items(b.frm)}
        for x in _outer_items(a.frm):
            name = place_of(x)
            if name in want:
                continue
            other = ("full" if isinstance(x, Left) else "left") + name[4:]
            if other in want:
                swapped = (Full if isinstance(x, Left) else Left)(x.left, x.right, x.on)
                yield self.step(replace(a, frm=_swap_item(a.frm, x, (swapped,), ())), "convert", "join_type", path, name, other)
            else:
                preds = x.left.preds + x.right.preds + x.on
                yield self.step(replace(a, frm=_swap_item(a.frm, x, x.left.items + x.right.items, preds)), "convert", "join_type", path, name, "inner join")
        own = {place_of(x) for x in _outer_items(a.frm)}
        for name, y in want.items():
            null, kept = ir.aliases(y.right), ir.aliases(y.left)
            items = {x.alias: x for x in a.frm.items if isinstance(x, ir.RELATIONS)}
            if name in own or not isinstance(y, Left) or not null <= set(items) or not kept & set(items):
                continue
            right = tuple(items[k] for k in sorted(null))
            left = tuple(items[k] for k in sorted(kept & set(items)))
            on_text, null_text = {text(p) for p in y.on}, {text(p) for p in y.right.preds}
            on, below, above = [], [], []
            for p in a.frm.preds:
                crosses = free_rels(p) & null and free_rels(p) - null
                (on if text(p) in on_text or crosses else below if text(p) in null_text else above).append(p)
            rest = tuple(x for x in a.frm.items if x not in right and x not in left)
            new = Group((*rest, Left(Group(left), Group(right, tuple(below)), tuple(on))), tuple(above))
            yield self.step(replace(a, frm=new), "convert", "join_type", path, "inner join", name)


def _outputs(q: Any) -> tuple:
    while isinstance(q, ir.SetOp):
        q = q.parts[0]
    return q.items


def _unmatched(own: tuple, want: tuple) -> list[tuple[int, Any]]:
    left = Counter(map(text, want))
    out = []
    for k, x in enumerate(own):
        t = text(x)
        if left[t] > 0:
            left[t] -= 1
        else:
            out.append((k, x))
    return out


def _outer_items(g: Group) -> Iterator[Any]:
    for x in g.items:
        if isinstance(x, (Left, Full)):
            yield x
            yield from _outer_items(x.left)
            yield from _outer_items(x.right)


def _swap_item(g: Group, old: Any, new: tuple, preds: tuple) -> Group:
    if old in g.items:
        return Group(tuple(y for x in g.items for y in (new if x == old else (x,))), g.preds + preds)
    return replace(g, items=tuple(replace(x, left=_swap_item(x.left, old, new, preds), right=_swap_item(x.right, old, new, preds)) if isinstance(x, (Left, Full)) else x for x in g.items))


def _drop_relation(g: Group, alias: str) -> Group | None:
    for x in g.items:
        if isinstance(x, ir.RELATIONS) and x.alias == alias:
            return replace(g, items=tuple(y for y in g.items if y is not x))
        if isinstance(x, (Left, Full)) and alias in ir.aliases(x):
            for side in ("left", "right"):
                if alias in ir.aliases(getattr(x, side)):
                    rest = _drop_relation(getattr(x, side), alias)
                    if rest is None:
                        return None
                    if rest.items:
                        new: tuple = (replace(x, **{side: rest}),)
                        return _swap_item(g, x, new, ())
                    return _swap_item(g, x, x.left.items, x.left.preds) if side == "right" and isinstance(x, Left) and not x.on and not x.right.preds else None
    return None


def edit_place(q: Select, place: str, old: Any, new: Any) -> Select:
    """The block with one condition removed, changed or added at a place."""

    def preds(own: tuple) -> tuple:
        if old is None:
            return (*own, new)
        k = own.index(old)
        return own[:k] + own[k + 1 :] if new is None else (*own[:k], new, *own[k + 1 :])

    def group(g: Group, here: str) -> Group:
        items = []
        for x in g.items:
            if isinstance(x, (Left, Full)):
                name = place_of(x)
                x = replace(x, left=group(x.left, f"{name}/kept"), right=group(x.right, f"{name}/null"), on=preds(x.on) if name == place else x.on)
            items.append(x)
        return Group(tuple(items), preds(g.preds) if here == place else g.preds)

    return replace(q, frm=group(q.frm, ""))
