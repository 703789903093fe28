"""Token counts of whole texts: lengths only, never ids, leave Python.

Long texts are split at safe boundaries, here white space: where a file's pattern
drops white space and no merge crosses it, the count of a text is the sum over its
words. Words already seen come from a bounded cache; new ones go to the library in
batches balanced by bytes. Whether a file is of that kind is read from the file;
the texts of any other (.json), and those of sentencepiece models (.model), whose
pieces carry white space, go to their library whole, in batches balanced by bytes.

Defined results: a null or empty text has 0 bytes and 0 tokens; repeated rows
are counted each; only ``doc_id`` and the text column are read, so further
columns of any name don't matter.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_bytes, kept_by_worker, lean_worker, text_or_empty
from .units import UnitCache, paused_collector

#: Bytes of new words for one call of the library.
BATCH_BYTES = 64 << 10
_TAIL = ".,;:!?"
_TO_SPACE = str.maketrans("\n\t\r", "   ")


def byte_balanced(words: list[str], limit: int = BATCH_BYTES) -> Iterator[list[str]]:
    """``words`` in order, in lists of about ``limit`` bytes; a longer word is alone."""
    part, held = [], 0
    for w in words:
        n = len(w.encode())
        if part and held + n > limit:
            yield part
            part, held = [], 0
        part.append(w)
        held += n
    if part:
        yield part


class WordCounter:
    """``encode_lengths(list of strings)`` gives the library's token count of each."""

    def __init__(self, encode_lengths, limit: int = 500_000):
        self.encode_lengths = encode_lengths
        self._cores = UnitCache(self._ask, limit)
        self._words = UnitCache(self._count, limit)

    def _ask(self, words: list[str]) -> list[int]:
        return [n for part in byte_balanced(words) for n in self.encode_lengths(part)]

    def _count(self, words: list[str]) -> list[int]:
        """A run of closing marks behind a letter or digit is a piece of its own."""
        split = []
        for w in words:
            core = w.rstrip(_TAIL)
            split.append((core, w[len(core) :]) if core and core[-1].isalnum() else (w, ""))
        got = self._cores.resolve([x for pair in split for x in pair if x])
        return [(got[a] if a else 0) + (got[b] if b else 0) for a, b in split]

    def counts(self, texts: list[str]) -> list[int]:
        with paused_collector():
            return self._counts(texts)

    def _counts(self, texts: list[str]) -> list[int]:
        split = [t.translate(_TO_SPACE).split(" ") if "\n" in t or "\t" in t or "\r" in t else t.split(" ") for t in texts]
        got = self._words.resolve([w for words in split for w in words])
        get = got.__getitem__
        return [sum(map(get, words)) for words in split]


class TextCounter:
    """Whole texts to the library: nothing is assumed about its boundaries."""

    def __init__(self, encode_lengths):
        self.encode_lengths = encode_lengths

    def counts(self, texts: list[str]) -> list[int]:
        return [n for part in byte_balanced(texts) for n in self.encode_lengths(part)]


# The pattern of the word vocabulary and its normaliser, for which words can be counted alone.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORD_NORMALIZERS = ("NFC", "Replace", "Lowercase")


def counts_by_words(spec: dict) -> bool:
    """Whether a tokenizers file drops white space and cuts words as WORD_PATTERN does."""
    steps = (spec.get("pre_tokenizer") or {}).get("pretokenizers") or [{}]
    first = steps[0]
    normalizers = tuple(n["type"] for n in (spec.get("normalizer") or {}).get("normalizers", ()))
    own = first.get("type") == "Split" and first.get("pattern", {}).get("Regex") == WORD_PATTERN and first.get("behavior") == "Removed"
    rest = all(step.get("type") == "ByteLevel" and not step.get("add_prefix_space") and not step.get("use_regex") for step in steps[1:])
    special = any(any(c.isspace() for c in t["content"]) for t in spec["added_tokens"])
    return own and rest and normalizers == WORD_NORMALIZERS and not special


@kept_by_worker
@lru_cache(maxsize=2)
def worker_counter(path: str) -> WordCounter | TextCounter:
    if path.endswith(".model"):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        return TextCounter(lambda texts: [len(ids) for ids in model.encode(texts, num_threads=1)])
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(path)
    library.no_truncation()
    library.no_padding()

    def lengths(texts: list[str]) -> list[int]:
        return [len(e) for e in library.encode_batch_fast(texts, add_special_tokens=False)]

    with open(path, encoding="utf-8") as f:
        return WordCounter(lengths) if counts_by_words(json.load(f)) else TextCounter(lengths)


def token_counts(docs: DataFrame, path: str, limit: int = 2048, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every document.

    One pass without a shuffle; each Arrow slice holds about 4 MB of text or one
    longer text, so tasks are balanced by bytes and not by rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lean_worker(worker_counter)
        counter = worker_counter(path)
        for batch in by_bytes(batches, "text"):
            n = pa.array(counter.counts(batch.column(1).to_pylist()), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pc.binary_length(batch.column(1)).cast(pa.int64()), n], ["doc_id", "n_bytes", "n_tokens"])

    src = docs.select(F.col(id_col).alias("doc_id"), text_or_empty(text_col).alias("text"))
    counted = src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_bytes long, n_tokens long")
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
