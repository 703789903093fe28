"""Personal data by anchor expansion.

One Aho-Corasick pass over a text finds anchors: at-signs, plus signs, digits,
URL schemes and identifier cues. From each anchor a local parser expands to the
boundaries of what stands there and validates it, so the text is not scanned
again for every kind. Each kind takes matches from left to right without
overlaps, as a scan with its pattern would; a match that fails validation is
dropped and its characters are not tried again.

Kinds, in order: email, ip, card, phone (the base); url, secret (the value behind
a cue such as ``token =``) and account (identifiers behind a cue, bank account
numbers by their check digits). Spans count code points, the end is exclusive.

Defined results: a null text counts as empty; an empty text has no spans and the
SHA-256 of nothing; repeated rows are searched each; very long texts and runs
take linear time, hostile ones too: a parser reads either a bounded stretch, or
what no later anchor of its kind reads again. Cues count in any case.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, lean_worker, text_or_empty

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "url", "secret", "account")

# The base patterns' parts, and cues.
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
SCHEMES = ("http://", "https://", "ftp://", "mailto:")
SECRET_CUES = ("token", "api_key", "apikey", "api-key", "secret", "password", "passwd", "access_key")
ACCOUNT_CUES = ("iban", "account", "acct", "ssn", "passport")

_DIGITS = re.compile(r"[0-9]+")
_URL = re.compile(r"[^\s<>\"'`{}|\\^\[\]]+")
_HOST = re.compile(r"(?:[^\s/@<>\"'`{}|\\^\[\]]{0,256}@)?(?:[A-Za-z0-9-]+\.)+[A-Za-z0-9-]+")
_GIVES = re.compile(r"[\"']?[ \t]{0,8}[=:][ \t]{0,8}[\"']?")
_VALUE = re.compile(r"[A-Za-z0-9_+/.~=-]{8,}")
_ACCOUNT = re.compile(r"(?:[ \t]{0,4}(?:number|no|nr|id)\b)?[ \t]{0,4}[.#:=]?[ \t]{0,4}([A-Z]{0,3}[0-9](?:[ -]?[0-9A-Z]){5,33})")


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def bank_account(text: str) -> bool:
    """An international account number whose remainder by 97 is one."""
    s = re.sub(r"[ -]", "", text)
    if not re.fullmatch(r"[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}", s):
        return False
    return int("".join(str(int(c, 36)) for c in s[4:] + s[:4])) % 97 == 1


@lru_cache(maxsize=1)
def automaton():
    import ahocorasick

    found = ahocorasick.Automaton()
    for c in "0123456789":
        found.add_word(c, ("digit", 1))
    found.add_word("@", ("at", 1))
    found.add_word("+", ("plus", 1))
    for kind, words in (("scheme", SCHEMES), ("secret", SECRET_CUES), ("account", ACCOUNT_CUES)):
        for w in words:
            found.add_word(w, (kind, len(w)))
    found.make_automaton()
    return found


_LOWER = {c: c + 32 for c in range(ord("A"), ord("Z") + 1)}


def lowered(text: str) -> str:
    """``text`` in lower case, with every character at its place."""
    low = text.lower()
    return low if len(low) == len(text) else text.translate(_LOWER)


def find_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end), by kind in the order of KINDS and then by start."""
    done = dict.fromkeys(KINDS, 0)
    poor = 0  # the end of a run that held no secret: its parts hold none either
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in KINDS}
    for last, (anchor, size) in automaton().iter(lowered(text)):
        at = last + 1 - size
        if anchor == "digit":
            if at >= done["ip"]:
                m = IP.match(text, at)
                if m:
                    done["ip"] = m.end()
                    if all(int(part) <= 255 if len(part) < 20 else int(part.lstrip("0")[:4] or 0) <= 255 for part in m.group().split(".")):
                        out["ip"].append(m.span())
                else:
                    done["ip"] = _DIGITS.match(text, at).end()
            if at >= done["card"]:
                m = CARD.match(text, at)
                if m:
                    done["card"] = m.end()
                    if m.end() - at <= 38:
                        digits = m.group().replace(" ", "").replace("-", "")
                        if 16 <= len(digits) <= 19 and luhn(digits):
                            out["card"].append(m.span())
        elif anchor == "at":
            start = at
            while start > done["email"] and text[start - 1] in LOCAL:
                start -= 1
            m = DOMAIN.match(text, at + 1) if start < at else None
            if m:
                done["email"] = m.end()
                out["email"].append((start, m.end()))
        elif anchor == "plus":
            m = PHONE.match(text, at) if at >= done["phone"] else None
            if m:
                done["phone"] = m.end()
                if 8 <= sum(c.isdigit() for c in m.group()) <= 15:
                    out["phone"].append(m.span())
        elif anchor == "scheme":
            if at >= done["url"] and _HOST.match(text, last + 1):
                m = _URL.match(text, last + 1)
                done["url"] = m.end()
                out["url"].append((at, last + 1 + len(m.group().rstrip(".,;:!?)"))))
        elif at < done[anchor] or (at and text[at - 1].isalnum()):
            continue
        elif anchor == "secret":
            gives = _GIVES.match(text, last + 1)
            m = _VALUE.match(text, gives.end()) if gives and gives.end() >= poor else None
            if m:
                value = m.group().rstrip(".=")
                if sum(c.isdigit() for c in value) >= 2:
                    done["secret"] = m.end()
                    out["secret"].append((m.start(), m.start() + len(value)))
                else:
                    poor = m.end()
        else:
            m = _ACCOUNT.match(text, last + 1)
            if m:
                value = m.group(1).rstrip(" -")
                if sum(c.isdigit() for c in value) >= 6 or bank_account(value):
                    done["account"] = m.start(1) + len(value)
                    out["account"].append((m.start(1), done["account"]))
    return [(k, a, b) for k in KINDS for a, b in out[k]]


def redact(text: str, spans: list[tuple[str, int, int]]) -> str:
    """Each span, overlapping ones together, replaced by its kind in angle brackets."""
    parts, at, end = [], 0, 0
    for start, stop, kind in sorted((a, b, k) for k, a, b in spans):
        if start >= end:
            parts += [text[at:start], f"<{kind.upper()}>"]
        end = max(end, stop)
        at = end
    return "".join([*parts, text[at:]])


def written(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def find_pii(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, spans array<struct<kind, start, end>>: one pass, no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for batch in by_bytes(batches, "text"):
            spans = [[dict(zip(("kind", "start", "end"), s, strict=True)) for s in find_spans(t)] for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(spans, kind)], ["doc_id", "spans"])

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, spans array<struct<kind:string,start:bigint,end:bigint>>")


def redact_documents(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` with the spans in its text replaced; a null text stays null, other columns pass through."""
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker()
        for batch in by_bytes(batches, text_col):
            at = names.index(text_col)
            texts = [None if t is None else redact(t, find_spans(t)) for t in batch.column(at).to_pylist()]
            yield batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))

    return docs.mapInArrow(run, docs.schema)


def digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, a count of each base kind, base_sha256, spans."""
    found = find_pii(docs, id_col, text_col)

    def of(*kinds: str) -> Column:
        return F.filter("spans", lambda s: s["kind"].isin(*kinds))

    def joined(spans: Column) -> Column:
        return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")

    counts = [F.size(of(k)).cast("long").alias(f"n_{k}") for k in BASE]
    return found.select("doc_id", *counts, F.sha2(joined(of(*BASE)).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))
