"""A small SQL front end for the query class: one block, key joins, conjunctions, grouped aggregates."""

from __future__ import annotations

import datetime as dt
import re

from runstore.catalog import SCHEMAS
from runstore.spec import Agg, Join, Pred, StarQuery

_TOKEN = re.compile(r"\s*(?:(\d+\.\d+|\d+)|'((?:[^']|'')*)'|([A-Za-z_][\w.]*)|(<=|>=|<>|!=|[=<>(),*;]))")
#: Tables in the order in which they are joined.
_ORDER = ("lineitem", "events", "documents", "orders", "customer", "supplier", "part", "nation", "region")
_FUNCTIONS = {"count", "sum", "min", "max", "avg"}
_OWNER = {c.strip().split(" ")[0]: t for t in _ORDER for c in SCHEMAS[t].split(",")}


class _Outside(Exception):
    """The text is not of the class."""


def _tokens(text: str) -> list[tuple[str, object]]:
    out, at = [], 0
    text = text.strip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise _Outside
        number, string, word, mark = m.groups()
        if number is not None:
            out.append(("value", float(number) if "." in number else int(number)))
        elif string is not None:
            out.append(("value", string.replace("''", "'")))
        elif word is not None:
            out.append(("word", word.lower().split(".")[-1]))
        elif mark != ";":
            out.append(("mark", "<>" if mark == "!=" else mark))
        at = m.end()
    return out


class _Reader:
    def __init__(self, tokens: list[tuple[str, object]]):
        self.tokens, self.at = tokens, 0

    def peek(self) -> tuple[str, object]:
        return self.tokens[self.at] if self.at < len(self.tokens) else ("end", None)

    def take(self, *wanted: object) -> object:
        kind, v = self.peek()
        if wanted and v not in wanted or kind == "end":
            raise _Outside
        self.at += 1
        return v

    def skip(self, *wanted: object) -> bool:
        for k, w in enumerate(wanted):
            if self.at + k >= len(self.tokens) or self.tokens[self.at + k][1] != w:
                return False
        self.at += len(wanted)
        return True

    def value(self, col: str) -> object:
        self.skip("timestamp") or self.skip("date")
        kind, v = self.peek()
        if kind != "value":
            raise _Outside
        self.at += 1
        if _kind(col) == "timestamp_ntz":
            return dt.datetime.fromisoformat(str(v))
        return v


def _kind(col: str) -> str:
    if col not in _OWNER:
        raise _Outside
    return next(c.strip().split(" ")[1] for c in SCHEMAS[_OWNER[col]].split(",") if c.strip().split(" ")[0] == col)


def _item(r: _Reader) -> str | Agg:
    word = r.take()
    if word in _FUNCTIONS and r.skip("("):
        distinct = r.skip("distinct")
        col = None if r.skip("*") else str(r.take())
        r.take(")")
        fn = "count_distinct" if distinct and word == "count" else str(word)
        if distinct and word != "count" or col is None and word != "count" or col is not None and col not in _OWNER:
            raise _Outside
        alias = str(r.take()) if r.skip("as") else f"{fn}_{col or 'rows'}"
        return Agg(fn, col, alias)
    if word not in _OWNER:
        raise _Outside
    return str(word)


def _comparison(r: _Reader) -> Pred | tuple[str, str]:
    col = str(r.take())
    if col not in _OWNER:
        raise _Outside
    if r.skip("between"):
        lo = r.value(col)
        r.take("and")
        return Pred(col, "between", (lo, r.value(col)))
    if r.skip("in", "("):
        values = [r.value(col)]
        while r.skip(","):
            values.append(r.value(col))
        r.take(")")
        return Pred(col, "in", tuple(values))
    if r.skip("like"):
        return Pred(col, "like", r.value(col))
    if r.skip("is"):
        no = r.skip("not")
        r.take("null")
        return Pred(col, "not null" if no else "null")
    op = r.take("=", "<>", "<", "<=", ">", ">=")
    kind, v = r.peek()
    if kind == "word" and v in _OWNER:
        r.take()
        if op != "=":
            raise _Outside
        return col, str(v)
    return Pred(col, str(op), r.value(col))


def parse(text: str) -> StarQuery | None:
    """The query, or None for anything outside the class."""
    try:
        return _parse(text)
    except (_Outside, ValueError):
        return None


def _parse(text: str) -> StarQuery:
    r = _Reader(_tokens(text))
    r.take("select")
    items = [_item(r)]
    while r.skip(","):
        items.append(_item(r))
    r.take("from")
    tables = [str(r.take())]
    equal: list[tuple[str, str]] = []
    preds: list[Pred] = []

    def conditions() -> None:
        while True:
            got = _comparison(r)
            (preds if isinstance(got, Pred) else equal).append(got)
            if not r.skip("and"):
                return

    while True:
        if r.skip(","):
            tables.append(str(r.take()))
        elif r.skip("join") or r.skip("inner", "join"):
            tables.append(str(r.take()))
            r.take("on")
            conditions()
        else:
            break
    if r.skip("where"):
        conditions()
    groups: list[str] = []
    if r.skip("group", "by"):
        groups.append(str(r.take()))
        while r.skip(","):
            groups.append(str(r.take()))
    order: list[str] = []
    if r.skip("order", "by"):
        order.append(str(r.take()))
        while r.skip(","):
            order.append(str(r.take()))
    limit = int(r.take()) if r.skip("limit") else None
    if r.peek()[0] != "end" or len(set(tables)) < len(tables) or not set(tables) <= set(_ORDER):
        raise _Outside
    columns = tuple(i for i in items if isinstance(i, str))
    aggs = tuple(i for i in items if isinstance(i, Agg))
    if aggs and set(columns) != set(groups) or groups and not aggs:
        raise _Outside
    left = sorted(tables, key=_ORDER.index)
    joins, have = [], {left[0]}
    while len(have) < len(tables):
        for a, b in [*equal, *[(b, a) for a, b in equal]]:
            if _OWNER[a] in have and _OWNER[b] not in have and _OWNER[b] in tables:
                joins.append(Join(_OWNER[b], a, b))
                have.add(_OWNER[b])
                break
        else:
            raise _Outside
    if len(joins) != len(equal):
        raise _Outside
    q = StarQuery(left[0], tuple(joins), tuple(preds), columns, aggs, tuple(order), limit)
    if not all(_OWNER[c] in have for c in q.needed):
        raise _Outside
    return q
