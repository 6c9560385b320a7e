"""Query trees: what the parser makes, what the rules rewrite and what distances compare.

Nodes are immutable, so that a tree can be a key. A Group is an n-ary inner join with its conjuncts; after the
syntactic rules the FROM and WHERE of a block are one Group, in which outer joins stand as Left or Full items.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, fields, replace
from typing import Any


@dataclass(frozen=True, slots=True)
class Col:
    rel: str | None
    name: str


@dataclass(frozen=True, slots=True)
class Lit:
    kind: str  # int, num, str, bool, null, date, timestamp, interval
    value: Any


@dataclass(frozen=True, slots=True)
class Fn:
    """A scalar function, an arithmetic operator, a cast or a CASE: compared as a whole."""

    name: str
    args: tuple = ()


@dataclass(frozen=True, slots=True)
class Agg:
    name: str
    arg: Any = None  # None: *
    distinct: bool = False


@dataclass(frozen=True, slots=True)
class Over:
    call: Any
    partition: tuple = ()
    order: tuple = ()


@dataclass(frozen=True, slots=True)
class Star:
    rel: str | None = None


@dataclass(frozen=True, slots=True)
class Cmp:
    op: str
    left: Any
    right: Any


@dataclass(frozen=True, slots=True)
class Same:
    """An equivalence class: all members are equal and none is null."""

    members: tuple


@dataclass(frozen=True, slots=True)
class And:
    args: tuple


@dataclass(frozen=True, slots=True)
class Or:
    args: tuple


@dataclass(frozen=True, slots=True)
class Not:
    arg: Any


@dataclass(frozen=True, slots=True)
class IsNull:
    arg: Any
    no: bool = False


@dataclass(frozen=True, slots=True)
class Like:
    arg: Any
    pattern: Any
    no: bool = False


@dataclass(frozen=True, slots=True)
class Between:
    arg: Any
    low: Any
    high: Any
    no: bool = False


@dataclass(frozen=True, slots=True)
class InList:
    arg: Any
    items: tuple
    no: bool = False


@dataclass(frozen=True, slots=True)
class InQuery:
    args: tuple
    query: Any
    no: bool = False


@dataclass(frozen=True, slots=True)
class Quant:
    op: str
    arg: Any
    every: bool
    query: Any


@dataclass(frozen=True, slots=True)
class Exists:
    query: Any
    no: bool = False


@dataclass(frozen=True, slots=True)
class Scalar:
    query: Any


@dataclass(frozen=True, slots=True)
class Table:
    name: str
    alias: str | None = None


@dataclass(frozen=True, slots=True)
class Derived:
    query: Any
    alias: str | None = None
    columns: tuple = ()
    lateral: bool = False


@dataclass(frozen=True, slots=True)
class Join:
    kind: str  # inner, cross, left, right, full
    left: Any
    right: Any
    on: Any = None
    using: tuple = ()
    natural: bool = False


@dataclass(frozen=True, slots=True)
class Group:
    items: tuple
    preds: tuple = ()


@dataclass(frozen=True, slots=True)
class Left:
    left: Group
    right: Group
    on: tuple = ()


@dataclass(frozen=True, slots=True)
class Full:
    left: Group
    right: Group
    on: tuple = ()


@dataclass(frozen=True, slots=True)
class Item:
    expr: Any
    name: str | None = None


@dataclass(frozen=True, slots=True)
class Key:
    expr: Any
    desc: bool = False
    nulls: str | None = None  # first, last


@dataclass(frozen=True, slots=True)
class Select:
    items: tuple
    frm: Any = None
    where: Any = None
    group: tuple = ()
    having: Any = None
    distinct: bool = False
    order: tuple = ()
    limit: Any = None
    offset: Any = None


@dataclass(frozen=True, slots=True)
class SetOp:
    kind: str  # union, intersect, except
    every: bool
    parts: tuple
    order: tuple = ()
    limit: Any = None
    offset: Any = None


@dataclass(frozen=True, slots=True)
class With:
    ctes: tuple  # (name, columns, query)
    body: Any


QUERIES = (Select, SetOp, With)
RELATIONS = (Table, Derived)


class GradingError(ValueError):
    """A query that cannot be graded; the message is for the student."""


class Unsupported(GradingError):
    pass


_FIELDS: dict[type, tuple[str, ...]] = {}


def names_of(node: Any) -> tuple[str, ...]:
    kind = type(node)
    if kind not in _FIELDS:
        _FIELDS[kind] = tuple(f.name for f in fields(kind)) if hasattr(kind, "__dataclass_fields__") else ()
    return _FIELDS[kind]


def rebuild(node: Any, fn: Callable[[Any], Any]) -> Any:
    """The node with ``fn`` applied to each child; the same object where nothing changes."""
    if isinstance(node, tuple):
        new = tuple(fn(x) for x in node)
        return node if all(a is b for a, b in zip(node, new)) else new
    changed = {}
    for name in names_of(node):
        old = getattr(node, name)
        if isinstance(old, (str, bool, int, float)) or old is None:
            continue
        new = rebuild(old, fn) if isinstance(old, tuple) else fn(old)
        if new is not old:
            changed[name] = new
    return replace(node, **changed) if changed else node


def rewrite(node: Any, fn: Callable[[Any], Any]) -> Any:
    """Bottom-up."""
    if not names_of(node):
        return node
    return fn(rebuild(node, lambda x: rewrite(x, fn) if not isinstance(x, tuple) else rebuild(x, lambda y: rewrite(y, fn))))


def walk(node: Any) -> Iterator[Any]:
    if isinstance(node, tuple):
        for x in node:
            yield from walk(x)
        return
    names = names_of(node)
    if names:
        yield node
        for name in names:
            x = getattr(node, name)
            if not isinstance(x, (str, bool, int, float)) and x is not None:
                yield from walk(x)


def columns(node: Any) -> set[Col]:
    return {x for x in walk(node) if isinstance(x, Col)}


def rels(node: Any) -> set[str]:
    return {x.rel for x in walk(node) if isinstance(x, Col)}


def substitute(node: Any, mapping: dict) -> Any:
    """Replaces whole expressions by equality."""
    if not mapping:
        return node
    return rewrite(node, lambda x: mapping.get(x, x) if isinstance(x, Col) else x) if not isinstance(node, tuple) else tuple(substitute(x, mapping) for x in node)


def rename(node: Any, mapping: dict[str, str]) -> Any:
    """Renames relation instances, where they stand and where they are referred to."""

    def one(x: Any) -> Any:
        if isinstance(x, Col) and x.rel in mapping:
            return Col(mapping[x.rel], x.name)
        if isinstance(x, RELATIONS) and x.alias in mapping:
            return replace(x, alias=mapping[x.alias])
        return x

    return rewrite(node, one)


def conjuncts(x: Any) -> tuple:
    if x is None:
        return ()
    if isinstance(x, And):
        return tuple(y for a in x.args for y in conjuncts(a))
    return (x,)


def conjunction(preds: tuple) -> Any:
    return None if not preds else preds[0] if len(preds) == 1 else And(tuple(preds))


def leaves(item: Any) -> Iterator[Any]:
    """The relations of a Group, below its outer joins too, but not inside derived tables."""
    if isinstance(item, RELATIONS):
        yield item
    elif isinstance(item, Group):
        for x in item.items:
            yield from leaves(x)
    elif isinstance(item, (Left, Full, Join)):
        yield from leaves(item.left)
        yield from leaves(item.right)


def aliases(item: Any) -> set[str]:
    return {x.alias for x in leaves(item)}


def has_aggregate(node: Any) -> bool:
    """Aggregates of this block: those of subqueries are their own."""
    if isinstance(node, Agg):
        return True
    if isinstance(node, tuple):
        return any(has_aggregate(x) for x in node)
    if isinstance(node, (*QUERIES, Over)):
        return False
    return any(has_aggregate(getattr(node, n)) for n in names_of(node) if not isinstance(getattr(node, n), (str, bool, int, float)))
