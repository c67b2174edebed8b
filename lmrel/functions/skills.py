"""Questions that the rule reasoner answers, each with a rule in Python and a twin in SQL.

In a twin ``{0}``, ``{1}`` stand for the input columns; the same text runs in Spark and DuckDB.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable
from dataclasses import dataclass


@dataclass(frozen=True)
class Skill:
    question: str
    dtype: str
    rule: Callable[..., object]
    sql: str
    options: tuple[str, ...] | None = None

    def twin(self, *columns: str) -> str:
        return self.sql.format(*columns)


_STOP = {"en": "the of and is that to in", "fr": "le les et des une que", "de": "der die und das ist ein", "es": "el los las que y del"}


def _language(text: str) -> str:
    votes = {k: sum(f" {w} " in f" {text.lower()} " for w in v.split()) for k, v in _STOP.items()}
    return max(sorted(votes), key=lambda k: votes[k])


def _votes(k: str) -> str:
    return " + ".join(f"(CASE WHEN concat(' ', lower({{0}}), ' ') LIKE '% {w} %' THEN 1 ELSE 0 END)" for w in _STOP[k].split())


def _language_sql() -> str:
    de, en, es, fr = (f"({_votes(k)})" for k in ("de", "en", "es", "fr"))
    return f"CASE WHEN {de} >= {en} AND {de} >= {es} AND {de} >= {fr} THEN 'de' WHEN {en} >= {es} AND {en} >= {fr} THEN 'en' WHEN {es} >= {fr} THEN 'es' ELSE 'fr' END"


_FIRST, _SECOND = "split_part({0}, ' ', 1)", "split_part({0}, ' ', 2)"
SIZE_BANDS = ("small", "medium", "large")
SKILLS = {
    "clean": Skill("Is this text clean?", "bool", lambda t: not re.search(r"[$%#*&]{3}", t), "NOT regexp_matches({0}, '[$%#*&]{{3}}')"),
    "failure": Skill("Does this describe a failure?", "bool", lambda t: t == "error", "{0} = 'error'"),
    "colour": Skill("What is the main colour?", "str", lambda t: t.split(" ")[0] if t.split(" ")[0] in ("red", "blue") else "none", f"CASE WHEN {_FIRST} IN ('red', 'blue') THEN {_FIRST} ELSE 'none' END", ("red", "blue", "none")),
    "red": Skill("Is it red?", "bool", lambda t: t.split(" ")[0] == "red", f"{_FIRST} = 'red'"),
    "thermal": Skill("Is it hot or cold?", "bool", lambda t: t.split(" ")[0] in ("hot", "cold"), f"{_FIRST} IN ('hot', 'cold')"),
    "ring": Skill("Is it a ring?", "bool", lambda t: t.split(" ")[1:2] == ["ring"], f"{_SECOND} = 'ring'"),
    "same_kind": Skill("Are both the same kind of thing?", "bool", lambda a, b: a.split(" ")[1:2] == b.split(" ")[1:2], "split_part({0}, ' ', 2) = split_part({1}, ' ', 2)"),
    "decade": Skill("Which decade is the date in?", "str", lambda d: str(int(d[:4]) // 10 * 10) + "s", "concat(CAST(CAST(floor(year({0}) / 10) * 10 AS INT) AS VARCHAR(9)), 's')", ("1980s", "1990s", "2000s", "2010s")),
    "segment": Skill("Which market is meant?", "str", lambda s: s.lower(), "lower({0})", ("automobile", "building", "furniture", "household", "machinery")),
    "kind24": Skill("Which kind and size class is it?", "str", lambda n, s: f"{n.split(' ')[1]}-{SIZE_BANDS[min(s // 17, 2)]}", "concat(split_part({0}, ' ', 2), CASE WHEN {1} < 17 THEN '-small' WHEN {1} < 34 THEN '-medium' ELSE '-large' END)"),
    "license": Skill("Does it mention a license?", "bool", lambda t: "license" in t.lower(), "lower({0}) LIKE '%license%'"),
    "contains": Skill("Is the passage in the text?", "bool", lambda t, p: p in t, "position({1} IN {0}) > 0"),
    "language": Skill("Which language is the text in?", "str", _language, _language_sql(), ("de", "en", "es", "fr")),
    "same_language": Skill("Are both texts in one language?", "bool", lambda a, b: _language(a) == _language(b), f"({_language_sql()}) = ({_language_sql().replace('{0}', '{1}')})"),
    "same_initial": Skill("Do both begin with the same letter?", "bool", lambda a, b: a[:1].lower() == b[:1].lower(), "lower(substr({0}, 1, 1)) = lower(substr({1}, 1, 1))"),
    "score": Skill("How long-winded is it, from 1 to 5?", "int", lambda t: 1 + min(4, len(t) // 1000), "1 + CAST(least(4, floor(length({0}) / 1000)) AS BIGINT)"),
    "json_band": Skill("Give k and its band.", "struct<k:bigint,band:string>", lambda p: {"k": (k := json.loads(p)["k"]), "band": "low" if k < 33 else "mid" if k < 66 else "high"}, ""),
    "tags": Skill("Which words describe it?", "list[str]", lambda t: t.split(" "), ""),
    "email": Skill("Is there an e-mail address?", "bool", lambda t: bool(re.search(r"[A-Za-z0-9.]+@[A-Za-z0-9]+\.[a-z]+", t)), "regexp_matches({0}, '[A-Za-z0-9.]+@[A-Za-z0-9]+[.][a-z]+')"),
    "longest": Skill("Which is the longest?", "str", lambda rows: sorted(rows, key=lambda r: (-len(r), r)), ""),
    "never": Skill("Is an alarm to be heard?", "bool", lambda s: False, "FALSE"),
    "loud": Skill("Is the recording loud?", "bool", lambda s: max(json.loads(s)) > 99, "{0} > 99"),
}
BY_QUESTION = {s.question: s for s in SKILLS.values()}
