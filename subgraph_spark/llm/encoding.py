"""Whole texts to token ids with the tokenizers library, fast on natural text.

The library splits a text into pre-tokens and merges inside each of them only. Texts of plain characters are split here, many
at a time: every byte has a class, and pre-tokens are runs of one class, put right for spaces and endings as the vocabulary's
pattern says. A pre-token of up to 16 bytes is a key of two integers. Its ids are looked up in an open-addressed table, all
keys together, and those that are new are merged by the library's model in one call. The table's size is bounded; when it
is full, it is begun anew. A text with a character beyond the plain ones, or with a special string, goes to the library whole.
"""

from __future__ import annotations

import functools
import os
import re
from collections.abc import Iterable, Iterator

import numpy as np

from .token_counts import byte_letters

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: Characters that aren't plain: beyond ASCII only some letters, signs and punctuation are, whose class the first byte tells.
_ODD = re.compile("[^\x01-\x7f\xa1-\xa9\xab-\xb1\xb4\xb6-\xb8\xbb\xbf\xc0-\xd6\xd8-\xf6\xf8-\xff\u2010-\u2027\u2030-\u205e\u20a0-\u20bf]")
_END, _SPACE, _LETTER, _NUMBER, _SIGN = range(5)
_KIND = np.full(256, _SIGN, np.uint8)
_KIND[[0, *b"\t\n\x0b\x0c\r ", *b"0123456789"]] = [_END, *[_SPACE] * 6, *[_NUMBER] * 10]
_KIND[[*range(0x41, 0x5B), *range(0x61, 0x7B), 0xC3]] = _LETTER
#: A place where any text may be cut.
_CUT = re.compile("(?<=[a-z]) (?=[a-z])")
#: Texts are cut into pieces of about this many characters, and pieces of about so many bytes are encoded together.
_PIECE, _GROUP = 1 << 20, 1 << 19
#: Pre-tokens that a worker remembers; about 90 bytes each.
MOST = 500_000
#: Masks for the first bytes of a word of eight.
_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
_MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9], np.uint64)
#: The letters that spell each byte; a zero parts words that are spelt together.
_SPELT = [" ", *byte_letters()[1:]]


def split(data: np.ndarray, keeps_space: bool) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end of each pre-token in ``data``: plain texts, a zero after each."""
    n = len(data)
    kind = _KIND[data]
    late = np.flatnonzero((data & 0xC0) == 0x80)
    for _ in range(2 if len(late) else 0):  # later bytes of a character are of its kind
        kind[late] = kind[late - 1]
    starts = np.flatnonzero(np.append(True, kind[1:] != kind[:-1]))
    ends, own = np.append(starts[1:], n), kind[starts]
    after = np.append(own[1:], _END)
    mark = np.zeros(n + 2, bool)
    mark[starts] = mark[n] = True
    if keeps_space:
        # White space before something else leaves it its last character, which is the other's if it is a space.
        other = ends[(own == _SPACE) & (after != _END)]
        mark[other - 1] = True
        mark[other[data[other - 1] == 0x20]] = False
    else:
        mark[np.flatnonzero(kind == _NUMBER)] = True
    # A lone apostrophe takes the letters of an ending with it.
    quote = starts[(own == _SIGN) & (after == _LETTER) & (ends - starts == 1)]
    quote = quote[(data[quote] == 0x27) & mark[quote]]
    one, two = data[quote + 1], data[quote + 2]
    taken = np.where(np.isin(one, list(b"stmd")), 1, 2 * ((np.isin(one, list(b"rv")) & (two == ord("e"))) | ((one == ord("l")) & (two == ord("l")))))
    quote, taken = quote[taken > 0], taken[taken > 0]
    mark[quote + 1] = False
    mark[quote + 1 + taken] = True
    cuts = np.flatnonzero(mark[: n + 1])
    kept = kind[cuts[:-1]] > (_END if keeps_space else _SPACE)
    return cuts[:-1][kept], cuts[1:][kept]


class PreTokenEncoder:
    """Encodes as ``Tokenizer.encode(text, add_special_tokens=False)`` does.

    ``keeps_space``: the vocabulary has the space at a word's front (byte level); else white space is dropped and letters are
    lowered. ``encode(texts)`` yields, per text, the ids as packed little-endian unsigned integers of ``width`` bytes.
    """

    def __init__(self, path: str, keeps_space: bool, most: int = MOST):
        from tokenizers import Tokenizer, pre_tokenizers

        self.library = Tokenizer.from_file(path)
        self._words = Tokenizer(self.library.model)
        self._words.pre_tokenizer = pre_tokenizers.WhitespaceSplit()
        self.width = 2 if self.library.get_vocab_size() <= 1 << 16 else 4
        self._type = np.dtype(f"<u{self.width}")
        self._keeps_space, self._most = keeps_space, most
        self._special = [x.content for x in self.library.get_added_tokens_decoder().values()]
        vocabulary, suffix = self.library.get_vocab(), self.library.model.end_of_word_suffix or ""
        self._bytes = np.zeros(max(vocabulary.values()) + 1, np.int32)
        for spelt, i in vocabulary.items():
            self._bytes[i] = len(spelt.removesuffix(suffix))
        # Half of the table stays free, whatever one group of texts adds.
        self._bits = (2 * (most + _GROUP // 2)).bit_length()
        self._clear()

    def _clear(self) -> None:
        size = 1 << self._bits
        self._low, self._high, self._start, self._count = np.zeros(size, np.uint64), np.zeros(size, np.uint64), np.zeros(size, np.uint32), np.zeros(size, np.uint32)
        self._pool, self._used, self._n = np.zeros(1 << 16, self._type), 0, 0

    def _whole(self, text: str) -> bytes:
        return np.array(self.library.encode_batch_fast([text], add_special_tokens=False)[0].ids, self._type).tobytes()

    def _merged(self, new: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of pre-tokens, each by itself, and how many each has."""
        raw = b"\0".join(new)
        ids = np.array(self._words.encode_batch_fast([raw.decode("latin-1").translate(_SPELT)], add_special_tokens=False)[0].ids, self._type)
        # Where each ends: tokens have known numbers of bytes, which add up to the pre-tokens' own.
        ends = np.append(np.flatnonzero(np.frombuffer(raw, np.uint8) == 0), len(raw)) - np.arange(len(new))
        reached = np.cumsum(self._bytes[ids], dtype=np.int64)
        last = np.searchsorted(reached, ends)
        if last[-1] != len(ids) - 1 or (reached[last] != ends).any():
            raise ValueError("the vocabulary lacks bytes")
        return ids, np.diff(last, prepend=-1)

    def _home(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        mixed = low * _MIX[0] ^ (high ^ high >> np.uint64(29)) * _MIX[1]
        return ((mixed ^ mixed >> np.uint64(32)) * _MIX[2] >> np.uint64(64 - self._bits)).astype(np.int64)

    def _find(self, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Where the keys are, or the free place at which the search for them ends."""
        place = self._home(low, high)
        there = self._low[place]
        open_ = np.flatnonzero((there != 0) & ((there != low) | (self._high[place] != high)))
        while len(open_):
            place[open_] = at = place[open_] + 1 & len(self._low) - 1
            there = self._low[at]
            open_ = open_[(there != 0) & ((there != low[open_]) | (self._high[at] != high[open_]))]
        return place

    def _add(self, low: np.ndarray, high: np.ndarray, start: np.ndarray, count: np.ndarray) -> None:
        """Put in distinct keys that aren't there."""
        place, todo = self._home(low, high), np.arange(len(low))
        while len(todo):
            free = todo[self._low[place[todo]] == 0]
            won = free[np.unique(place[free], return_index=True)[1]]
            at = place[won]
            self._low[at], self._high[at], self._start[at], self._count[at] = low[won], high[won], start[won], count[won]
            todo = np.setdiff1d(todo, won, assume_unique=True)
            place[todo] = place[todo] + 1 & len(self._low) - 1
        self._n += len(low)

    def _keep(self, ids: np.ndarray, upto: int) -> None:
        """Put ids behind those in the pool; the first ``upto`` of them stay."""
        if self._used + len(ids) > len(self._pool):
            self._pool = np.concatenate([self._pool[: self._used], np.zeros(max(len(self._pool), len(ids)), self._type)])
        self._pool[self._used : self._used + len(ids)] = ids
        self._used += upto

    def _group(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of some pieces of plain texts, one after another, and where each piece's end."""
        if self._n >= self._most:
            self._clear()
        raw = b"\0".join([*pieces, bytes(16)])
        data = np.frombuffer(raw, np.uint8)
        begin, end = split(data[:-16], self._keeps_space)
        words, length = np.ndarray(len(raw) - 7, "<u8", raw, strides=(1,)), end - begin
        low, high = words[begin] & _MASK[np.minimum(length, 8)], words[begin + 8] & _MASK[np.clip(length - 8, 0, 8)]
        place = self._find(low, high)
        long = np.flatnonzero(length > 16)
        missing = np.flatnonzero((self._low[place] == 0) & (length <= 16))
        start, count = self._start[place].astype(np.int64), self._count[place].astype(np.int64)
        if len(missing) or len(long):
            order = missing[np.lexsort((high[missing], low[missing]))]
            fresh = np.ones(len(order), bool)
            fresh[1:] = (low[order[1:]] != low[order[:-1]]) | (high[order[1:]] != high[order[:-1]])
            first = order[fresh]
            longs = {x: k for k, x in enumerate(dict.fromkeys(raw[a:b] for a, b in zip(begin[long].tolist(), end[long].tolist(), strict=True)), len(first))}
            ids, counts = self._merged([raw[a:b] for a, b in zip(begin[first].tolist(), end[first].tolist(), strict=True)] + list(longs))
            starts = self._used + np.cumsum(counts) - counts
            self._keep(ids, int(counts[: len(first)].sum()))
            self._add(low[first], high[first], starts[: len(first)], counts[: len(first)])
            of = np.cumsum(fresh) - 1
            start[order], count[order] = starts[of], counts[of]
            if len(long):
                of = np.array([longs[raw[a:b]] for a, b in zip(begin[long].tolist(), end[long].tolist(), strict=True)])
                start[long], count[long] = starts[of], counts[of]
        total = np.append(0, np.cumsum(count))
        ids = self._pool[np.repeat(start - total[:-1], count) + np.arange(total[-1])]
        return ids, total[np.searchsorted(begin, np.cumsum([len(x) + 1 for x in pieces]))]

    def _pieces(self, text: str) -> Iterator[bytes]:
        text = text if self._keeps_space else text.lower()
        at = 0
        while len(text) - at > _PIECE and (cut := _CUT.search(text, at + _PIECE)):
            yield text[at : cut.start()].encode()
            at = cut.start()
        yield (text[at:] if at else text).encode()

    def _joined(self, waiting: list[tuple[int, bytes]], out: list[list[bytes]]) -> None:
        """Append the ids of ``waiting``, which name the place in ``out`` that they belong to."""
        if waiting:
            ids, ends = self._group([x for _, x in waiting])
            packed, at = memoryview(ids.tobytes()), 0
            for (place, _), end in zip(waiting, (ends * self.width).tolist(), strict=True):
                out[place].append(packed[at:end])
                at = end

    def encode(self, texts: Iterable[str]) -> Iterator[bytes]:
        """Ids per text, in order; a piece of a text, or a group of short ones, is split at a time."""
        out: list[list[bytes]] = []
        waiting: list[tuple[int, bytes]] = []
        held = 0
        for text in texts:
            out.append([])
            if _ODD.search(text) or any(x in text for x in self._special):
                out[-1].append(self._whole(text))
            else:
                for piece in self._pieces(text):
                    waiting.append((len(out) - 1, piece))
                    held += len(piece)
                    if held >= _GROUP:
                        self._joined(waiting, out)
                        waiting, held = [], 0
            if not waiting:
                yield from map(b"".join, out)
                out = []
        self._joined(waiting, out)
        yield from map(b"".join, out)


@functools.lru_cache(maxsize=4)
def encoder_for(path: str, keeps_space: bool, most: int = MOST) -> PreTokenEncoder:
    """A worker's encoder: later tasks of the same worker find its pre-tokens known."""
    return PreTokenEncoder(path, keeps_space, most)
