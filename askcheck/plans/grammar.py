"""A small grammar of questions, the ground that rule-based stand-ins work on.

A template has a pattern with slots, and for each reading a query and the fact
that selects it. Stand-in generators fill templates; stand-in members parse a
question back with the same patterns. Nothing of a hidden fact or a gold query is
in the question, so what a member sees is what a model would see.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from ..sources.tables import DATABASES, FOREIGN_KEYS

#: By table: a number to measure, a column of few values, and how rows are called.
ROLES = {
    "region": ("r_regionkey", "r_name"),
    "nation": ("n_nationkey", "n_regionkey"),
    "customer": ("c_acctbal", "c_mktsegment"),
    "supplier": ("s_acctbal", "s_nationkey"),
    "part": ("p_retailprice", "p_brand"),
    "orders": ("o_totalprice", "o_orderstatus"),
    "lineitem": ("l_extendedprice", "l_returnflag"),
    "events": ("value", "event_type"),
    "documents": ("n_chars", "lang"),
    "labels": ("toxic", "quality"),
    "embeddings": ("vec_id", "label"),
    "pages": ("page_id", "url"),
    "benchmark": ("item_id", "text"),
    "conversations": ("turn", "role"),
}
#: Pairs of tables of one database with an attribute of the same name and meaning.
SHARED = {("customer", "supplier"): ("account balance", "c_acctbal", "s_acctbal"), ("orders", "lineitem"): ("status", "o_orderstatus", "l_linestatus"), ("part", "lineitem"): ("price", "p_retailprice", "l_extendedprice"), ("region", "nation"): ("name", "r_name", "n_name")}
#: Columns of one table whose names share a word.
OVERLAPS = {"lineitem": ("line figure", "l_linenumber", "l_linestatus"), "orders": ("order detail", "o_orderdate", "o_orderpriority"), "nation": ("nation key", "n_nationkey", "n_regionkey"), "customer": ("customer key", "c_custkey", "c_nationkey"), "part": ("part label", "p_brand", "p_type"), "events": ("event mark", "event_id", "event_type"), "documents": ("document mark", "lang", "source"), "labels": ("label value", "quality", "toxic"), "supplier": ("supplier key", "s_suppkey", "s_nationkey"), "embeddings": ("vector mark", "vec_id", "label"), "pages": ("page mark", "page_id", "url"), "conversations": ("turn mark", "conv_id", "turn")}


@dataclass(frozen=True)
class Reading:
    hidden: str
    sql: str


@dataclass(frozen=True)
class Filled:
    """A template filled: the question, its readings (empty if it has no answer), evidence, feedback."""

    subcategory: str
    nl: str
    readings: tuple[Reading, ...] = ()
    evidence: tuple[str, ...] = ()
    feedback: str = ""
    slots: dict = field(default_factory=dict, hash=False, compare=False)


def linked(db_id: str) -> set[tuple[str, str]]:
    """Pairs of tables of a database with a path of foreign keys, either way."""
    names = DATABASES[db_id]
    reach = {(t, t) for t in names} | {p for t, _, f, _ in FOREIGN_KEYS if t in names and f in names for p in ((t, f), (f, t))}
    while True:
        more = {(a, d) for a, b in reach for c, d in reach if b == c} - reach
        if not more:
            return reach
        reach |= more


def unlinked_pairs(db_id: str) -> list[tuple[str, str]]:
    reach = linked(db_id)
    names = sorted(DATABASES[db_id])
    return [(a, b) for i, a in enumerate(names) for b in names[i + 1 :] if (a, b) not in reach]


def fill(subcategory: str, db_id: str, t: str, variant: int = 0) -> Filled | None:
    """The template of ``subcategory`` on table ``t`` of ``db_id``; None where the schema doesn't allow it."""
    m, g = ROLES[t]
    slots = {"t": t, "m": m, "g": g, "db": db_id}
    count = f"SELECT {g}, count(*) AS n FROM {t} GROUP BY {g}"
    if subcategory == "plain":
        return Filled(subcategory, f"number of {t} per {g}", (Reading("", count),), slots=slots)
    if subcategory == "with_evidence":
        term = ("heavy", "notable", "leading")[variant % 3]
        share = (0.5, 0.75, 0.9)[variant % 3]
        rule = f"{term} {t} are those whose {m} exceeds its {share} quantile"
        return Filled(subcategory, f"number of {term} {t} per {g}", (Reading("", f"SELECT {g}, count(*) AS n FROM {t} WHERE {m} > (SELECT percentile({m}, {share}) FROM {t}) GROUP BY {g}"),), (rule,), slots=slots | {"term": term, "share": share})
    if subcategory == "scope":
        what = ("total", "greatest", "least")[variant % 3]
        f = {"total": "sum", "greatest": "max", "least": "min"}[what]
        return Filled(subcategory, f"{what} {m} for all {g} of {t}", (Reading(f"one figure over every {g} together", f"SELECT {f}({m}) AS v FROM {t}"), Reading(f"a figure for each {g} on its own", f"SELECT {g}, {f}({m}) AS v FROM {t} GROUP BY {g}")), slots=slots)
    if subcategory == "attachment":
        low, high = f"(SELECT min({g}) FROM {t})", f"(SELECT max({g}) FROM {t})"
        above = f"{m} > (SELECT avg({m}) FROM {t})"
        return Filled(
            subcategory,
            f"{t} of the first {g} and of the last {g} with {m} above the mean",
            (Reading(f"the bound on {m} belongs to the last {g} only", f"SELECT count(*) AS n FROM {t} WHERE {g} = {low} OR ({g} = {high} AND {above})"), Reading(f"the bound on {m} belongs to both {g} values", f"SELECT count(*) AS n FROM {t} WHERE ({g} = {low} OR {g} = {high}) AND {above}")),
            slots=slots,
        )
    if subcategory == "lexical_overlap":
        if t not in OVERLAPS:
            return None
        word, a, b = OVERLAPS[t]
        return Filled(subcategory, f"distinct values of the {word} of {t}", tuple(Reading(f"the {word} meant is {c}", f"SELECT count(DISTINCT {c}) AS n FROM {t}") for c in (a, b)), slots=slots | {"word": word})
    if subcategory == "entity":
        for (x, y), (word, a, b) in SHARED.items():
            if t == x and y in DATABASES[db_id]:
                return Filled(subcategory, f"highest {word} on record near {t}", (Reading(f"the {word} meant is that of {x}", f"SELECT max({a}) AS v FROM {x}"), Reading(f"the {word} meant is that of {y}", f"SELECT max({b}) AS v FROM {y}")), slots=slots | {"word": word, "other": y})
        return None
    if subcategory == "vagueness":
        term = ("large", "high", "considerable")[variant % 3]
        return Filled(subcategory, f"number of {t} with {term} {m}", (Reading(f"{term} means above the mean of {m}", f"SELECT count(*) AS n FROM {t} WHERE {m} > (SELECT avg({m}) FROM {t})"), Reading(f"{term} means in the top tenth of {m}", f"SELECT count(*) AS n FROM {t} WHERE {m} > (SELECT percentile({m}, 0.9) FROM {t})")), slots=slots | {"term": term})
    if subcategory == "user_knowledge":
        return Filled(subcategory, f"mean {m} of {t} of my {g}", tuple(Reading(f"my {g} is the {w} one", f"SELECT avg({m}) AS v FROM {t} WHERE {g} = (SELECT {f}({g}) FROM {t})") for w, f in (("first", "min"), ("last", "max"))), slots=slots)
    if subcategory == "conflict":
        notes = (f"the score of {t} is the mean of {m}", f"the score of {t} is the median of {m}")
        return Filled(subcategory, f"score of {t} per {g}", (Reading(f"take the mean of {m}", f"SELECT {g}, avg({m}) AS v FROM {t} GROUP BY {g}"), Reading(f"take the median of {m}", f"SELECT {g}, median({m}) AS v FROM {t} GROUP BY {g}")), notes, slots=slots)
    if subcategory == "missing_entity":
        thing = ("warehouse", "manager", "contract")[variant % 3]
        return Filled(subcategory, f"the {thing} of each of the {t}", feedback=f"no table or column holds a {thing}, so {t} cannot be listed with it; ask the database administrator to add it", slots=slots | {"thing": thing})
    if subcategory == "missing_relationship":
        pairs = [p for p in unlinked_pairs(db_id) if t in p]
        if not pairs:
            return None
        other = pairs[variant % len(pairs)][0 if pairs[variant % len(pairs)][1] == t else 1]
        return Filled(subcategory, f"the {other} that belong to each of the {t}", feedback=f"no relationship links {t} and {other}, so their rows cannot be matched; ask the database administrator for a key between them", slots=slots | {"other": other})
    if subcategory == "external_knowledge":
        scale = ("Nordic index points", "the 2019 reference currency", "regulatory grades")[variant % 3]
        return Filled(subcategory, f"{m} of {t} expressed in {scale}", feedback=f"the conversion of {m} to {scale} is neither stored nor defined; supply its rule to get an answer", slots=slots | {"scale": scale})
    text = ("please erase my entries from the {t}", "hello there, how are the {t} today", "write a poem about {t}")[variant % 3].format(t=t)
    return Filled("improper", text, feedback=f"the request is no query on this data about {t}; ask for something that can be read from its tables", slots=slots)


_NAME = r"(?P<t>[a-z]+)"
PATTERNS: dict[str, re.Pattern] = {
    k: re.compile(v)
    for k, v in {
        "with_evidence": rf"number of (?P<term>heavy|notable|leading) {_NAME} per (?P<g>\w+)",
        "plain": rf"number of {_NAME} per (?P<g>\w+)",
        "scope": rf"(?P<what>total|greatest|least) (?P<m>\w+) for all (?P<g>\w+) of {_NAME}",
        "attachment": rf"{_NAME} of the first (?P<g>\w+) and of the last \w+ with (?P<m>\w+) above the mean",
        "lexical_overlap": rf"distinct values of the (?P<word>[a-z ]+?) of {_NAME}",
        "entity": rf"highest (?P<word>[a-z ]+?) on record near {_NAME}",
        "vagueness": rf"number of {_NAME} with (?P<term>large|high|considerable) (?P<m>\w+)",
        "user_knowledge": rf"mean (?P<m>\w+) of {_NAME} of my (?P<g>\w+)",
        "conflict": rf"score of {_NAME} per (?P<g>\w+)",
        "missing_entity": rf"the (?P<thing>warehouse|manager|contract) of each of the {_NAME}",
        "missing_relationship": rf"the (?P<other>[a-z]+) that belong to each of the {_NAME}",
        "external_knowledge": rf"(?P<m>\w+) of {_NAME} expressed in (?P<scale>[\w ]+)",
        "improper": rf"(?:erase my entries from the|how are the|poem about) {_NAME}",
    }.items()
}
_VARIANTS = {"with_evidence": ("heavy", "notable", "leading"), "scope": ("total", "greatest", "least"), "vagueness": ("large", "high", "considerable"), "missing_entity": ("warehouse", "manager", "contract"), "external_knowledge": ("Nordic", "the 2019", "regulatory"), "improper": ("erase", "hello", "poem")}


def understand(nl: str, db_id: str) -> Filled | None:
    """The template that a question fills, with all its readings."""
    for name, pattern in PATTERNS.items():
        m = pattern.search(nl)
        if m and m["t"] in ROLES and m["t"] in DATABASES[db_id]:
            slots = m.groupdict()
            said = next((slots[k] for k in ("what", "term", "thing", "scale") if k in slots), nl).lower()
            variant = next((i for i, w in enumerate(_VARIANTS.get(name, ())) if w.lower() in said), 0)
            if name == "missing_relationship":
                pairs = [p for p in unlinked_pairs(db_id) if m["t"] in p]
                variant = next((i for i, p in enumerate(pairs) if m["other"] in p), 0)
            return fill(name, db_id, m["t"], variant)
    return None


def restyle(nl: str, style: str) -> str:
    """The wording of a style around the same core."""
    return {"formal": f"Kindly report the following: {nl}.", "colloquial": f"hey, get me the {nl}, ok", "interrogative": f"What is the {nl}?"}[style]


def style_of(nl: str) -> str:
    return "interrogative" if nl.rstrip().endswith("?") else "colloquial" if nl.startswith("hey") else "formal"
