"""Token counts without encoding: whole-token shortcut.

Offline, once per vocabulary: a vocabulary string that the merges rebuild from its bytes is one token whenever it
stands as a pre-token, whatever is around it. ``whole_tokens`` proves this for every entry by running the merges
themselves. Counting then splits a text into pre-tokens, counts each proven one as 1, and runs merges for the rest only.

The split is done here with the vocabulary's own pattern. Two regular expression engines can differ on rare or
unassigned code points, so a text with a character outside the ranges that were compared in full (``_COMPARED``; the
tests compare them again), or with a special string, is counted by the library itself.

Defined cases: a null text is empty and has no tokens; null and repeated ids are kept as they are, one row per row; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import functools
import os
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_arrow, whole_text

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: The pre-token pattern of the byte-level vocabularies.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Any character outside the ranges on which both engines agree.
_COMPARED = r"[^\x00-\u0557\u2010-\u2060\u20a0-\u20bf\u3001-\u30ff\u4e00-\u9fef]"
#: Texts are walked in pieces of about this many characters, cut where a space follows a letter and precedes one.
_PIECE = 1 << 20

COUNTS = "doc_id long, n_bytes long, n_tokens long"


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: printable ones for themselves, the others from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


def whole_tokens(library) -> set[str]:
    """The texts that the merges of a byte-level vocabulary make one token of, each proven by merging it."""
    byte_of = {x: b for b, x in enumerate(byte_letters())}
    proven = set()
    for spelt in library.get_vocab(with_added_tokens=False):
        if all(x in byte_of for x in spelt) and len(library.model.tokenize(spelt)) == 1:
            try:
                proven.add(bytes(byte_of[x] for x in spelt).decode())
            except UnicodeDecodeError:  # part of a character: never a pre-token
                continue
    return proven


class TokenCounter:
    """``count(text)`` is ``len(library.encode(text, add_special_tokens=False).ids)``."""

    def __init__(self, path: str, most: int = 200_000):
        import regex
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self._special = [x.content for x in self.library.get_added_tokens_decoder().values()]
        self._letters = {b: x for b, x in enumerate(byte_letters())}
        self.whole = whole_tokens(self.library)
        self._split, self._odd, self._cut = regex.compile(PATTERN).findall, regex.compile(_COMPARED).search, regex.compile(r"(?<=[a-z]) (?=[a-z])")
        self._merged: dict[str, int] = {}
        self._most = most

    def _merge(self, pre_token: str) -> int:
        n = self._merged.get(pre_token)
        if n is None:
            n = len(self.library.model.tokenize(pre_token.encode().decode("latin-1").translate(self._letters)))
            if len(pre_token) <= 64:
                self._merged[pre_token] = n
        return n

    def _pieces(self, text: str) -> Iterator[str]:
        at = 0
        while len(text) - at > _PIECE and (cut := self._cut.search(text, at + _PIECE)):
            yield text[at : cut.start()]
            at = cut.start()
        yield text[at:] if at else text

    def count(self, text: str) -> int:
        if self._odd(text) or any(x in text for x in self._special):
            return len(self.library.encode(text, add_special_tokens=False).ids)
        if len(self._merged) > self._most:
            self._merged.clear()
        n, whole, merge = 0, self.whole, self._merge
        for piece in self._pieces(text):
            pre_tokens = self._split(piece)
            rest = [x for x in pre_tokens if x not in whole]
            n += len(pre_tokens) - len(rest) + sum(map(merge, rest))
        return n


@functools.lru_cache(maxsize=2)
def counter_for(path: str) -> TokenCounter:
    """A worker's counter: the proof is made once, and later tasks find merges known."""
    return TokenCounter(path)


def count_tokens(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows ``COUNTS`` per document. Nothing is shuffled."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = None
        for batch in batches:
            counter = counter or counter_for(tokenizer)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([counter.count(x.as_py()) for x in batch.column(2)], pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    text = whole_text(text_col)
    return in_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text")), count, COUNTS)
