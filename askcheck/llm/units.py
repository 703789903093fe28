"""Encoding of whole texts through a cache of space-separated units.

A single space between two other non-space characters always begins a new piece
of the byte-level patterns, so what lies between two such spaces can be encoded
alone and the results joined. Words repeat, so most units come from a bounded
cache; the library only sees what the cache does not hold.
"""

from __future__ import annotations

import gc
import json
import re
from array import array
from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager
from functools import lru_cache
from itertools import accumulate, chain

import numpy as np

from .common import kept_by_worker

#: White space right before a space: only then may a space be inside a piece.
_UNSAFE = re.compile(r"\s ")
_SAFE_SPACE = re.compile(r"(?<=\S) (?=\S)")
#: Longer units are encoded each time and not kept.
LONGEST_KEPT = 48


class UnitCache:
    """Unit -> encoded value, of at most two generations of ``limit`` entries.

    When the younger generation is full it becomes the older one; what is asked
    for again moves back, so frequent units stay and memory stays bounded.
    """

    def __init__(self, encode_many: Callable[[list[str]], Iterable], limit: int = 600_000):
        self.encode_many, self.limit = encode_many, limit
        self.young: dict = {}
        self.old: dict = {}

    def resolve(self, units: list[str]) -> dict:
        """A mapping that holds every one of ``units``."""
        missing = set(units).difference(self.young)
        if not missing:
            return self.young
        if len(self.young) + len(missing) > self.limit:
            self.old, self.young = self.young, {}
            missing = set(units)
        again = missing.intersection(self.old)
        found = dict(zip(again, map(self.old.__getitem__, again), strict=True))
        ask = list(missing.difference(again))
        found.update(zip(ask, self.encode_many(ask), strict=True))
        long = {u: found.pop(u) for u in ask if len(u) > LONGEST_KEPT}
        self.young.update(found)
        return {**self.young, **long} if long else self.young


def split_units(text: str) -> list[str]:
    """Units of ``text``; each but the first has lost the space before it."""
    if _UNSAFE.search(text) or text[:1] == " " or text[-1:] == " ":
        return _SAFE_SPACE.split(text)
    return text.split(" ")


@contextmanager
def paused_collector() -> Iterator[None]:
    """Without the cycle collector, which would walk the caches again and again; nothing here makes cycles."""
    on = gc.isenabled()
    gc.disable()
    try:
        yield
    finally:
        if on:
            gc.enable()


class TextEncoder:
    """Ids of whole texts as little-endian unsigned 32-bit bytes.

    ``encode_many`` gives the ids of each string of a list.
    """

    def __init__(self, encode_many: Callable[[list[str]], Iterable], limit: int = 600_000):
        def first(units: list[str]) -> list[bytes]:
            lists = list(encode_many(units))
            ends = list(accumulate(map(len, lists)))
            flat = array("I", chain.from_iterable(lists)).tobytes()
            return [flat[4 * a : 4 * b] for a, b in zip([0, *ends], ends, strict=False)]

        self._first = UnitCache(first, limit // 10)
        self._rest = UnitCache(lambda units: first([" " + u for u in units]), limit)

    def encode(self, texts: list[str]) -> list[bytes]:
        with paused_collector():
            return self._encode(texts)

    def _encode(self, texts: list[str]) -> list[bytes]:
        split = [split_units(t) for t in texts]
        heads = [u[0] for u in split]
        head = self._first.resolve(heads)
        rest = self._rest.resolve([x for u in split for x in u[1:]])
        get = rest.__getitem__
        return [head[u[0]] + b"".join(map(get, u[1:])) if len(u) > 1 else head[u[0]] for u in split]


def byte_alphabet() -> dict[str, int]:
    """The printable stand-ins that byte-level vocabularies use for bytes."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in set(shown)]
    return {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(hidden)}


@kept_by_worker
@lru_cache(maxsize=2)
def byte_level_encoder(path: str, limit: int = 600_000) -> TextEncoder:
    """An encoder equal to the tokenizers library's for a byte-level BPE file.

    The vocabulary and its special strings are read from the library's file; new
    units are merged by tiktoken with the same ranks, which is several times
    faster for single words. Special strings inside texts become special ids,
    the library's default.
    """
    import public_tokenizers
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    special = {t["content"]: t["id"] for t in spec["added_tokens"]}
    letters = byte_alphabet()
    ranks = {bytes(letters[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
    engine = tiktoken.Encoding("units", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)
    plain, allowed = engine._core_bpe.encode_ordinary, set(special)
    lead = min(special, key=len)[:2] if special else ""

    whole = engine._core_bpe.encode_single_piece

    def encode_many(units: list[str]) -> list[list[int]]:
        # letters after at most one space are a single piece
        return [
            whole(u.encode()) if u[1:].isalpha() and (u[0] == " " or u[0].isalpha()) else engine.encode(u, allowed_special=allowed, disallowed_special=()) if lead and lead in u else plain(u)
            for u in units
        ]

    return TextEncoder(encode_many, limit)


def ids_array(encoded: bytes) -> np.ndarray:
    return np.frombuffer(encoded, "<u4")
