"""Prompt texts: a constant head per call site (so servers can reuse its prefix), then the row."""

from __future__ import annotations

import json
import re

_POOL = {
    ("boolean", False): ("Is the item alive?", {"item": "a sleeping cat"}, "true"),
    ("bigint", False): ("How many legs are there?", {"items": "two dogs"}, "8"),
    ("double", False): ("What is the share in percent?", {"part": "one half"}, "50.0"),
    ("date", False): ("On which day was it sent?", {"note": "sent on the second of May 2020"}, "2020-05-02"),
    ("string", True): ("Which size fits?", {"item": "elephant"}, "large"),
    ("array", False): ("Which fruits are named?", {"note": "an apple and a pear"}, '["apple", "pear"]'),
    ("struct", False): ("Give the parts.", {"item": "red ball"}, '{"colour": "red", "thing": "ball"}'),
    ("string", False): ("Which animal is it?", {"sound": "miaow"}, "cat"),
}


class ExamplePool:
    """One worked example, chosen by the kind of answer and whether options are given."""

    @staticmethod
    def pick(ddl: str, has_options: bool) -> tuple[str, dict, str]:
        kind = re.split(r"[<(]", ddl)[0]
        return _POOL.get((kind, has_options)) or _POOL.get((kind, False)) or _POOL["string", has_options]


def _kind(ddl: str, sizes: tuple[int, int | None] | None) -> str:
    if ddl.startswith("array"):
        low, high = sizes or (0, None)
        count = f"exactly {low}" if low == high else f"{low} or more" if high is None else f"{low} to {high}"
        return f"Reply with a JSON list of {count} items, each of type {ddl[6:-1]}."
    return f"Reply with one value of type {ddl} and nothing else."


def map_head(question: str, ddl: str, options=None, sizes=None, examples: bool = True) -> str:
    lines = ["You fill one cell of a table from the given fields of its row.", _kind(ddl, sizes)]
    if examples:
        q, fields, reply = ExamplePool.pick(ddl, bool(options))
        lines += [f"Example task: {q}", f"Example row: {json.dumps(fields)}", f"Example reply: {reply}"]
    lines.append(f"Task: {question}")
    if options:
        lines.append("Allowed replies: " + json.dumps(list(options), ensure_ascii=False))
    return "\n".join(lines) + "\n"


def render_map_prompt(question: str, row_json: str, ddl: str, options=None, sizes=None, examples: bool = True, layout: str = "prefix") -> str:
    """``layout='reference'`` puts the options behind the row, at the price of a shorter shared prefix."""
    if layout == "reference" and options:
        return map_head(question, ddl, None, sizes, examples) + f"Row: {row_json}\nAllowed replies: {json.dumps(list(options), ensure_ascii=False)}\nReply:"
    return map_head(question, ddl, options, sizes, examples) + f"Row: {row_json}\nReply:"


#: What parts the values of a reply to several rows.
SEPARATOR = ";"


def render_batch_prompt(question: str, rows: list[str], ddl: str, options=None, sizes=None, examples: bool = True) -> str:
    """One prompt for several rows (the earlier release's way)."""
    listed = "\n".join(f"{i}. {row}" for i, row in enumerate(rows, 1))
    return map_head(question, ddl, options, sizes, examples) + f"Rows:\n{listed}\nReply with one value for each of the {len(rows)} rows, in their order, with {SEPARATOR} between them.\nReply:"


def render_ask_prompt(question: str, context_json: str | None = None, ddl: str = "string", options=None, sizes=None) -> str:
    lines = ["Answer briefly.", _kind(ddl, sizes), f"Question: {question}"]
    if context_json is not None:
        lines.append(f"Table: {context_json}")
    if options:
        lines.append("Choose from: " + json.dumps(list(options), ensure_ascii=False))
    return "\n".join(lines) + "\nReply:"


def approx_tokens(text: str) -> int:
    """One token for each four characters, rounded up: a rule that SQL can repeat."""
    return -(-len(text) // 4)
