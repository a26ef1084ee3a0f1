"""Token ids of a byte-level vocabulary file, many texts at once.

Between two non-spaces a space always begins a new word of the vocabulary's pattern, so a
text is the ids of its words, each with the space before it. Each distinct word is merged
once: the words that a batch meets for the first time go through the merges together, and
a batch's ids are then gathered by array. Texts in which white space meets white space
across a space, and texts with special tokens, go through the merges whole.
"""

from __future__ import annotations

import base64
import json
import re
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np

_ENCODERS: dict[str, "Encoder"] = {}
#: Characters of text that are turned into ids at once.
AT_ONCE = 500_000


class Slots(dict):
    """Word -> slot; a word met first gets the next one and is noted in `new`."""

    def __init__(self):
        super().__init__()
        self.new: list = []

    def __missing__(self, word):
        self[word] = slot = len(self)
        self.new.append(word)
        return slot


class Encoder:
    """Ids of a byte-level vocabulary: those of `tokenizers` for a JSON file, special tokens' strings included, or
    those of `tiktoken` for a file of ranks, which has no special tokens. Remembers about `most` words."""

    def __init__(self, path: str, pattern: str, most: int = 250_000):
        import tiktoken

        if path.endswith(".tiktoken"):
            with open(path, "rb") as f:
                special, ranks = {}, {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        else:
            with open(path, encoding="utf-8") as f:
                spec = json.load(f)
            letters = {c: b for b, c in byte_letters().items()}
            special = {t["content"]: t["id"] for t in spec["added_tokens"]}
            ranks = {bytes(letters[c] for c in word): i for word, i in spec["model"]["vocab"].items() if word not in special}
        self.special = special
        self.any_special = re.compile("|".join(map(re.escape, sorted(special, key=len, reverse=True))) or r"(?!)")
        self.merges = tiktoken.Encoding("vocabulary", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.bytes_of = np.zeros(max(ranks.values()) + 1, np.int64)
        for word, i in ranks.items():
            self.bytes_of[i] = len(word)
        self.most = most
        self.forget()

    def forget(self) -> None:
        self.known = Slots()
        self.start, self.size = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64)
        self.edges = np.zeros(1 << 16, np.uint8)  # 1: begins with white space, 2: ends with it; an empty word is a space
        self.ids, self.used = np.zeros(1 << 18, np.uint32), 0

    def _put(self, slots: np.ndarray, ids: np.ndarray, sizes: np.ndarray) -> None:
        """The ids of the words in these slots, one after the other, and how many each has."""
        while self.used + len(ids) > len(self.ids):
            self.ids = np.r_[self.ids, np.zeros_like(self.ids)]
        self.size[slots] = sizes
        self.start[slots] = self.used + np.cumsum(sizes) - sizes
        self.ids[self.used : self.used + len(ids)] = ids
        self.used += len(ids)

    def _meet(self) -> None:
        """Learns new words: strings follow a space, tuples of one string begin a text, numbers are ids themselves."""
        words, first = self.known.new, len(self.known) - len(self.known.new)
        self.known.new = []
        while len(self.known) > len(self.start):
            self.start, self.size, self.edges = (np.r_[x, np.zeros_like(x)] for x in (self.start, self.size, self.edges))
        edges = np.fromiter(map(_edges, words), np.uint8, len(words))
        self.edges[first : first + len(words)] = edges
        plain = np.flatnonzero(edges == 0)
        follow = [w for w in (words[k] for k in plain) if type(w) is str]
        if follow:
            ids = np.array(self.merges(" " + " ".join(follow)), np.uint32)
            ends = np.cumsum([len(w.encode()) + 1 for w in follow])
            last = np.searchsorted(np.cumsum(self.bytes_of[ids]), ends) + 1
            self._put(first + np.array([k for k in plain if type(words[k]) is str]), ids, np.diff(last, prepend=0))
        others = [k for k, w in enumerate(words) if edges[k] or type(w) is not str]
        if others:
            got = [[w] if type(w) is int else self.merges(w[0] if type(w) is tuple else " " + w) for w in (words[k] for k in others)]
            self._put(first + np.array(others), np.array(list(chain.from_iterable(got)), np.uint32), np.array(list(map(len, got))))

    def whole(self, text: str) -> np.ndarray:
        """The ids of one text, without the memory of words."""
        out, at = [], 0
        for m in self.any_special.finditer(text):
            out += [*self.merges(text[at : m.start()]), self.special[m[0]]]
            at = m.end()
        return np.array([*out, *self.merges(text[at:])], np.uint32)

    def encode(self, texts: list[str | None], tail: int | None = None) -> list[np.ndarray]:
        """The ids of each text, and `tail` at the end of each."""
        if not texts:
            return []
        lists, apart = [], set()
        for k, text in enumerate(texts):
            words: list = (text or "").split(" ")
            words[0] = (words[0],)
            if tail is not None:
                words.append(tail)
            lists.append(words)
            if text and any(x in text for x in self.special):
                apart.add(k)
        words = list(chain.from_iterable(lists))
        if len(self.known) > self.most:
            self.forget()
        at = np.fromiter(map(self.known.__getitem__, words), np.int64, len(words))
        if self.known.new:
            self._meet()
        sizes = self.size[at]
        ends = np.cumsum(sizes)
        ids = self.ids[np.repeat(self.start[at] - (ends - sizes), sizes) + np.arange(ends[-1])]
        last = np.cumsum(list(map(len, lists)))
        cuts = ends[last - 1]
        out = [ids[a:b] for a, b in zip([0, *cuts[:-1]], cuts)]
        runs = np.flatnonzero((self.edges[at[:-1]] & 2) & (self.edges[at[1:]] << 1))
        for k in apart.union(np.searchsorted(last, runs, "right").tolist()):
            ids = self.whole(texts[k])
            out[k] = ids if tail is None else np.append(ids, np.uint32(tail))
        return out


def _edges(word) -> int:
    if type(word) is int:
        return 0
    if type(word) is tuple:
        return 2 * word[0][-1:].isspace()
    return 3 if not word else word[0].isspace() + 2 * word[-1].isspace()


def in_parts(texts: list[str | None], most: int = AT_ONCE) -> Iterator[tuple[int, list[str | None]]]:
    """(position, texts) of parts of at most so many characters, or of one text."""
    at = n = 0
    for k, text in enumerate(texts):
        size = len(text or "")
        if k > at and n + size > most:
            yield at, texts[at:k]
            at, n = k, 0
        n += size
    if at < len(texts):
        yield at, texts[at:]


def byte_letters() -> dict[int, str]:
    """How byte-level vocabularies write bytes: printable Latin-1 as it is, the others from code point 256 on."""
    plain = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    others = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(others)}


def encoder(name: str, most: int = 250_000) -> Encoder:
    if name not in _ENCODERS:
        import public_tokenizers as P

        _ENCODERS[name] = Encoder(P.path(name), P.PATTERN, most)
    return _ENCODERS[name]


def encoded(name: str, texts: list[str | None], tail: int | None = None) -> Iterable[np.ndarray]:
    """The ids of each text, one after the other."""
    enc = encoder(name)
    for _, part in in_parts(texts):
        yield from enc.encode(part, tail)
