"""Byte-pair encoding by last tokens: what greedy merging does, told from pairs of neighbours.

A merge sequence is the right one exactly if every two neighbours in it would not have merged otherwise. So a
prefix has one right last token: the one that fits the right last token of the shorter prefix before it.
"""

from __future__ import annotations

import json

MAX_PAIRS = 1_000_000


def byte_letters() -> dict[str, int]:
    """Letter of byte-level vocabularies to byte: printable bytes stand for themselves, the others follow from U+0100 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + k): b for k, b in enumerate(others)}


class Vocabulary:
    """Tokens of a tokenizer file as bytes, the merge that made each, and the test for neighbours."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        suffix = model.get("end_of_word_suffix") or ""
        letters = byte_letters()
        self.names = {v: k for k, v in model["vocab"].items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names |= {v: k for k, v in self.special.items()}
        raw = lambda name: bytes(letters[c] for c in name)
        self.inner: dict[bytes, int] = {}
        self.final: dict[bytes, int] = {}
        self.length: dict[int, int] = {}
        self.made: dict[int, tuple[int, int, int]] = {}  # token -> (rank, left, right)
        self.rank: dict[tuple[int, int], int] = {}
        vocab = model["vocab"]
        for rank, pair in enumerate(model["merges"]):
            left, right = pair if isinstance(pair, list) else pair.split(" ", 1)
            a, b, t = vocab[left], vocab[right], vocab[left + right]
            self.rank[a, b] = rank
            self.made.setdefault(t, (rank, a, b))
        for name, token in vocab.items():
            ends = bool(suffix) and name.endswith(suffix) and name != suffix
            stem = name[: -len(suffix)] if ends else name
            if token in self.made or len(stem) == 1:
                (self.final if ends else self.inner)[raw(stem)] = token
                self.length[token] = len(stem)
        if not suffix:
            self.final = self.inner
        self.pairs: dict[int, bool] = {}

    def neighbours(self, a: int, b: int) -> bool:
        """Whether greedy merging leaves token b right after token a."""
        key = a << 20 | b
        found = self.pairs.get(key)
        if found is None:
            if len(self.pairs) >= MAX_PAIRS:
                self.pairs.clear()
            found = self.pairs[key] = self._stay_apart(a, b)
        return found

    def _stay_apart(self, a: int, b: int) -> bool:
        """Undo the latest merge on either side of the seam, again and again; no pair across it may have come before."""
        ceiling = 1 << 30
        while True:
            if self.rank.get((a, b), ceiling) < ceiling:
                return False
            made_a, made_b = self.made.get(a), self.made.get(b)
            if made_a is None and made_b is None:
                return True
            if made_b is None or (made_a is not None and made_a[0] > made_b[0]):
                ceiling, a = made_a[0], made_a[2]
            else:  # of two like merges the left one comes first, so the right one is undone first
                ceiling, b = made_b[0] + 1, made_b[1]

    def last_token(self, word: bytes, at: int, last: list[int], tokens: dict[bytes, int]) -> int:
        """The right last token of word[:at], given those of all shorter prefixes (last[0] is a stand-in)."""
        for begin in range(max(0, at - 64), at):
            token = tokens.get(word[begin:at])
            if token is not None and (begin == 0 or self.neighbours(last[begin], token)):
                return token
        for begin in range(max(0, at - 64) - 1, -1, -1):  # tokens longer than 64 bytes
            token = tokens.get(word[begin:at])
            if token is not None and (begin == 0 or self.neighbours(last[begin], token)):
                return token
        raise ValueError("a byte is not in the vocabulary")


def lcp(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    lo = 0
    while a[lo] == b[lo]:
        lo += 1
    return lo


class PrefixTrie:
    """Encodes sets of distinct words as one walk through their trie, depth first.

    The sorted words are the trie's leaves in order. The stack of last tokens along the current path is cut
    back to the branching node and grown from there, so the state of a shared prefix is computed once.
    """

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary

    def encode(self, words: list[bytes]) -> dict[bytes, list[int]]:
        v, out = self.v, {}
        path, last = b"", [-1]
        for word in sorted(words):
            if not word:
                out[word] = []
                continue
            del last[min(lcp(path, word), len(last) - 1) + 1 :]
            for at in range(len(last), len(word)):
                last.append(v.last_token(word, at, last, v.inner))
            path = word[: len(last) - 1]
            token = v.last_token(word, len(word), last, v.final)
            ids, at = [token], len(word) - v.length[token]
            while at:
                ids.append(last[at])
                at -= v.length[last[at]]
            out[word] = ids[::-1]
        return out
