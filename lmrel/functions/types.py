"""Return types of language-model functions: parsing, inference from the surrounding syntax, list sizes."""

from __future__ import annotations

import re

_SIMPLE = {"bool": "boolean", "boolean": "boolean", "int": "bigint", "float": "double", "str": "string", "string": "string", "date": "date", "timestamp": "timestamp_ntz"}


def parse_type(name: str) -> str:
    """Spark DDL of a declared return type: simple names, decimal(p,s), list[T], struct<...> or DDL."""
    name = name.strip()
    if m := re.fullmatch(r"(?:list|List)\[(.+)\]", name):
        return f"array<{parse_type(m[1])}>"
    return _SIMPLE.get(name, name)


def infer_return_type(template: str, peer: str | None = None) -> str:
    """The type that a call has in an expression such as ``{} = TRUE``, ``{} > 3`` or ``explode({})``.

    ``peer`` is the type of a column it is compared with, if any.  A string literal in IN or = gives
    str without making it an option list, so an answer outside stays possible.
    """
    t = template.strip().upper()
    if t in ("{}", "NOT {}", "NOT ({})") or re.search(r"\{\}\s*(=|<>|!=|IS)\s*(NOT\s+)?(TRUE|FALSE)\b", t):
        return "bool"
    if re.search(r"(EXPLODE|POSEXPLODE|SIZE|ARRAY_CONTAINS)\(\s*\{\}", t):
        return "list[str]"
    if peer:
        return {"bigint": "int", "int": "int", "double": "float", "string": "str", "boolean": "bool"}.get(peer, peer)
    if re.search(r"\{\}\s*(=|<>|<=|>=|<|>)\s*(DATE|TIMESTAMP)\s*'", t):
        return "date" if "DATE '" in t else "timestamp"
    if re.search(r"\b(SUM|AVG)\(\s*\{\}|\{\}\s*(=|<>|<=|>=|<|>|BETWEEN)\s*-?\d+\.\d|\{\}\s*/", t):
        return "float"
    if re.search(r"\{\}\s*(=|<>|<=|>=|<|>|BETWEEN|[-+*])\s*-?\d", t):
        return "int"
    return "str"


def parse_quantifier(q: str | None) -> tuple[int, int | None]:
    """Least and most items of a list: ``*``, ``+``, ``?``, ``{n}``, ``{m,n}`` or ``{m,}`` (None: any)."""
    if q in (None, "", "*"):
        return 0, None
    if q in ("+", "?"):
        return (1, None) if q == "+" else (0, 1)
    m = re.fullmatch(r"\{(\d+)(,(\d*))?\}", q)
    if not m:
        raise ValueError(f"not a quantifier: {q}")
    low = int(m[1])
    high = low if m[2] is None else int(m[3]) if m[3] else None
    if high is not None and high < low:
        raise ValueError(f"empty range: {q}")
    return low, high
