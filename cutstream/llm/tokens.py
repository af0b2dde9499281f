"""Token ids of texts with a public byte-level BPE file, for packing and for token files.

The tokenizers library makes every id. As most of its time goes to words it has met before, a batch of texts is split into
the words of the file's pre-tokenizer by array operations, and each distinct word is encoded once per worker; its ids are
kept in a bounded hash table. The split is exact for characters whose class no Unicode version changed (Latin, Greek,
Cyrillic and neighbours, general punctuation); a text with any other character goes to the library whole.
"""

from __future__ import annotations

import json
import os
from functools import lru_cache

import numpy as np
import regex

from cutstream.llm.common import _powers, mix, table64

VOCABULARY = "byte_bpe_50k.json"
CACHE_WORDS = 1_000_000
_SLOTS = 1 << 21
_TOP = 0x2060
#: Characters outside the array split: controls, and what lies beyond the ranges whose classes are settled.
_ODD = regex.compile(r"[\x00-\x08\x0E-\x1F\x7F-\x9F\u0530-\u200F\u2028-\u202F\u205F-\U0010FFFF]")
_WHITE, _LETTER, _NUMBER, _OTHER = range(4)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


@lru_cache(maxsize=1)
def _classes() -> np.ndarray:
    chars = [chr(i) for i in range(_TOP)]
    white, letter, number = (regex.compile(p) for p in (r"\s", r"\p{L}", r"\p{N}"))
    return np.array([_WHITE if white.match(c) else _LETTER if letter.match(c) else _NUMBER if number.match(c) else _OTHER for c in chars], np.uint8)


_VALUES = table64(41, _TOP)


def split_words(points: np.ndarray, begins: np.ndarray) -> np.ndarray:
    """Where words begin in the code points of texts put end to end; begins: of the texts, none of them empty.

    A run of letters, of numbers or of other signs is a word, together with one blank just before it. White space is a
    word up to its last character if something follows, which then stands alone unless it is that blank. An apostrophe
    that begins a word takes the letters of an English contraction with it, and no more.
    """
    kind = _classes()[points]
    white = kind == _WHITE
    first = np.zeros(len(points), bool)
    first[begins] = True
    change = np.empty(len(points), bool)
    change[1:] = kind[1:] != kind[:-1]
    change |= first
    change[0] = True
    last_white = np.zeros(len(points), bool)  # white space just before something else of the same text
    last_white[:-1] = white[:-1] & ~white[1:] & ~first[1:]
    after_blank = np.zeros(len(points), bool)
    after_blank[1:] = (points[:-1] == 0x20) & ~first[1:]
    start = (white & (change | last_white)) | (~white & change & ~after_blank)
    quote = np.flatnonzero((points == 0x27) & start)
    if len(quote):
        n = len(points)
        at = lambda i: np.where((i < n) & ~first[np.minimum(i, n - 1)], points[np.minimum(i, n - 1)], 0)
        a = at(quote + 1)
        b = np.where(a > 0, at(quote + 2), 0)
        one = np.isin(a, [ord(c) for c in "stmd"])
        two = ((a == ord("r")) & (b == ord("e"))) | ((a == ord("v")) & (b == ord("e"))) | ((a == ord("l")) & (b == ord("l")))
        hit = one | two
        quote, width = quote[hit], np.where(two[hit], 2, 1)
        start[quote + 1] = False
        after = quote + 1 + width
        after = after[after < n]
        start[after] |= kind[after] == _LETTER
    return np.flatnonzero(start)


class Encoder:
    """ids(texts) -> (all ids, end of each text's ids); special tokens' strings are ordinary text."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tool = Tokenizer.from_file(path)
        self.tool.encode_special_tokens = True
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        step = made.get("pre_tokenizer") or {}
        self.plain = step.get("type") == "ByteLevel" and step.get("use_regex", True) and not step.get("add_prefix_space") and not made.get("normalizer")
        line = self.tool.encode("\n", add_special_tokens=False).ids
        self.plain = self.plain and len(line) == 1
        self.line = line[0] if line else -1
        self.clear()

    def clear(self) -> None:
        self.keys = np.zeros(_SLOTS, np.uint64)
        self.values = np.zeros(_SLOTS, np.int32)
        self.flat = np.zeros(1 << 20, np.uint32)
        self.ends = np.zeros(1 << 18, np.int64)  # of each word's ids in flat; word i begins where i - 1 ends
        self.known = 0

    def whole(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(x.ids, np.uint32) for x in self.tool.encode_batch_fast(texts, add_special_tokens=False)]

    def _find(self, h: np.ndarray) -> np.ndarray:
        at = (h & np.uint64(_SLOTS - 1)).astype(np.int64)
        there = self.keys[at]
        out = np.where(there == h, self.values[at], -1)
        open_ = np.flatnonzero((there != h) & (there != 0))
        at = at[open_]
        while len(open_):
            at = (at + 1) & (_SLOTS - 1)
            there = self.keys[at]
            hit = there == h[open_]
            out[open_[hit]] = self.values[at[hit]]
            more = ~hit & (there != 0)
            open_, at = open_[more], at[more]
        return out

    def _put(self, h: np.ndarray) -> None:
        value = np.arange(self.known, self.known + len(h), dtype=np.int32)
        at = (h & np.uint64(_SLOTS - 1)).astype(np.int64)
        while len(h):
            free = self.keys[at] == 0
            self.keys[at[free]] = h[free]
            done = free & (self.keys[at] == h)
            self.values[at[done]] = value[done]
            h, value, at = h[~done], value[~done], (at[~done] + 1) & (_SLOTS - 1)

    def _learn(self, h: np.ndarray, words: list[str]) -> None:
        """Encode new words. Those without a line feed go through the library in one text, a line each."""
        lines = [i for i, w in enumerate(words) if "\n" not in w and not w[-1].isspace()]
        ids, n = np.zeros(0, np.uint32), np.zeros(0, np.int64)
        if lines:
            ids = self.whole(["\n".join(words[i] for i in lines)])[0]
            cut = np.flatnonzero(ids == self.line)
            n = np.diff(np.concatenate([[-1], cut, [len(ids)]])) - 1
            ids = np.delete(ids, cut)
        rest = sorted(set(range(len(words))) - set(lines))
        other = self.whole([words[i] for i in rest]) if rest else []
        ids = np.concatenate([ids, *other])
        n = np.concatenate([n, [len(x) for x in other]]).astype(np.int64)
        if len(n) != len(words):
            raise AssertionError("a word was not encoded by itself")
        used = int(self.ends[self.known - 1]) if self.known else 0
        while used + len(ids) > len(self.flat):
            self.flat = np.concatenate([self.flat, np.zeros_like(self.flat)])
        while self.known + len(words) > len(self.ends):
            self.ends = np.concatenate([self.ends, np.zeros_like(self.ends)])
        self.flat[used : used + len(ids)] = ids
        self.ends[self.known : self.known + len(words)] = used + np.cumsum(n)
        self._put(h[np.array(lines + rest, np.int64)])
        self.known += len(words)

    def ids(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        odd = [i for i, t in enumerate(texts) if t and (not self.plain or _ODD.search(t))]
        odd_ids = dict(zip(odd, self.whole([texts[i] for i in odd]), strict=True)) if odd else {}
        even = [i for i, t in enumerate(texts) if t and i not in odd_ids]
        ends = np.zeros(len(texts), np.int64)
        flat = np.zeros(0, np.uint32)
        if even:
            text = "".join(texts[i] for i in even)
            points = np.frombuffer(text.encode("utf-32-le"), "<u4")
            begins = np.cumsum([0, *(len(texts[i]) for i in even)])
            word = split_words(points, begins[:-1])
            stop = np.append(word[1:], len(points))
            up, down = _powers(len(points) + 1)
            total = np.zeros(len(points) + 1, np.uint64)
            np.cumsum(_VALUES[points] * up[: len(points)], out=total[1:])
            h = mix((total[stop] - total[word]) * down[word] + (stop - word).astype(np.uint64))
            h[h == 0] = 1
            code = self._find(h)
            miss = np.flatnonzero(code < 0)
            if len(miss):
                fresh, at = np.unique(h[miss], return_index=True)
                if self.known + len(fresh) > CACHE_WORDS:
                    self.clear()
                    fresh, at = np.unique(h, return_index=True)
                    miss = np.arange(len(h))
                self._learn(fresh, [text[a:b] for a, b in zip(word[miss[at]].tolist(), stop[miss[at]].tolist(), strict=True)])
                code[miss] = self._find(h[miss])
            end = self.ends[code]
            n = end - np.where(code > 0, self.ends[code - 1], 0)
            total_ids = np.concatenate([[0], np.cumsum(n)])
            flat = self.flat[np.repeat(end - total_ids[1:], n) + np.arange(total_ids[-1])]
            ends[even] = np.diff(total_ids[np.searchsorted(word, begins)])
        if odd:
            own = np.split(flat, np.cumsum(ends[even])[:-1]) if even else []
            parts = dict(zip(even, own, strict=True)) | odd_ids
            flat = np.concatenate([parts[i] for i in sorted(parts)])
            ends[odd] = [len(odd_ids[i]) for i in odd]
        return flat, np.cumsum(ends)


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    return Encoder(path)
