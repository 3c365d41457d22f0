"""Texts to token ids with the tokenizers library, asking its model only for words it has not encoded before.

Texts are cut into the words that the tokenizer's own pre-tokenizer would make, all texts of a piece at once by
comparing the kinds of neighbouring characters; the kind of a character is asked of the pre-tokenizer itself.
Every distinct word is encoded by the library's model and kept in a table that compares words byte by byte.
Texts that hold a string of a special token, and, for the vocabulary that folds case and composes characters,
texts with letters from U+0250 on, go to the library as a whole, so the ids are always its own.
"""

from __future__ import annotations

import re

import numpy as np
from tokenizers import Tokenizer

from .texts import flat, held
from .word_table import Grown, WordTable

# Letters and numbers below U+0250; \s is spelt out since libraries differ on control characters.
_L = "A-Za-zªµºÀ-ÖØ-öø-ɏ"
_N = "0-9²³¹¼-¾"
_S = r" \t\n\r\f\v"
#: A text with one of these is cut by the library.
UNUSUAL = re.compile("[\x00\x1c-\x1f\x85\xa0ɐ-\U0010ffff]|<\\|")
_SHORT = "'(?:[stmd]|re|ve|ll)"
PATTERNS = {
    "byte": re.compile(f"{_SHORT}| ?[{_L}]+| ?[{_N}]+| ?[^{_S}{_L}{_N}]+|[{_S}]+(?![^{_S}])|[{_S}]+"),
    "word": re.compile(f"{_SHORT}|[{_L}]+|[{_N}]|[^{_S}{_L}{_N}]+"),
}


def plain(text: str) -> bool:
    return UNUSUAL.search(text) is None


def cut(text: str, kind: str) -> list[str]:
    """Words of a plain text; the word vocabulary folds case first (no final-sigma rule applies below U+0250)."""
    return PATTERNS[kind].findall(text.lower() if kind == "word" else text)


# ---------------------------------------------------------------- words of many texts at once
LETTER, NUMBER, OTHER, WHITE, SPACE, UNKNOWN = range(6)


class Kinds:
    """The kind of each character, asked of the library's own cutting when first met."""

    def __init__(self, library: Tokenizer, spaced: bool):
        self.cutter, self.spaced = library.pre_tokenizer, spaced
        self.table = np.full(0x110000, UNKNOWN, np.uint8)
        self.table[32] = SPACE

    def _ask(self, c: str) -> int:
        spans = lambda t: [span for _, span in self.cutter.pre_tokenize_str(t)]
        joins = lambda t: spans(t) == [(0, 2)]
        if joins("a" + c):
            return LETTER
        if joins("." + c):
            return OTHER
        if joins("1" + c):
            return NUMBER
        # a character in no run: white space, or a number where each stands alone
        return WHITE if self.spaced or len(spans("." + c)) == 1 else NUMBER

    def of(self, codes: np.ndarray) -> np.ndarray:
        kinds = self.table[codes]
        if (kinds == UNKNOWN).any():
            for c in np.unique(codes[kinds == UNKNOWN]).tolist():
                self.table[c] = self._ask(chr(c))
            kinds = self.table[codes]
        return kinds


def word_spans(codes: np.ndarray, kinds: np.ndarray, firsts: np.ndarray, spaced: bool) -> tuple[np.ndarray, np.ndarray]:
    """(starts, ends) of the words of texts that stand behind each other and begin at `firsts`.

    spaced: white space is part of the words (a space goes with the word behind it); else it parts them, and
    each number character is a word.
    """
    n = len(codes)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    new = np.zeros(n + 3, bool)  # a text begins here; beyond the end as well
    new[firsts[firsts < n]] = True
    new[n:] = True
    group = np.minimum(kinds, WHITE)
    start = np.zeros(n + 3, bool)
    np.not_equal(group[1:], group[:-1], out=start[1:n])
    start |= new
    white = group == WHITE
    if spaced:
        behind = np.flatnonzero(start[1:n] & white[:-1] & ~white[1:] & ~new[1:n]) + 1
        start[behind - 1] = True
        start[behind[kinds[behind - 1] == SPACE]] = False
    else:
        start[:n] |= group == NUMBER
    # shortened verbs: an apostrophe that begins a word takes the letters along
    quotes = np.flatnonzero((codes == 39) & start[:n])
    if len(quotes):
        one, two = (codes[np.minimum(quotes + k, n - 1)] for k in (1, 2))
        short = np.isin(one, [ord(c) for c in "stmd"]) & ~new[quotes + 1]
        long = (((one == ord("r")) | (one == ord("v"))) & (two == ord("e")) | (one == ord("l")) & (two == ord("l"))) & ~new[quotes + 1] & ~new[quotes + 2]
        start[quotes[short | long] + 1] = False
        start[quotes[long] + 2] = False
        start[quotes[short] + 2] = True
        start[quotes[long] + 3] = True
    starts = np.flatnonzero(start[:n])
    ends = np.append(starts[1:], n)
    if not spaced:
        keep = ~white[starts]
        starts, ends = starts[keep], ends[keep]
    return starts, ends


#: Words made ready for the model at once.
LEARN = 10_000
#: Characters of the byte-level alphabet: visible Latin-1 characters stand for themselves, the other bytes follow from U+0100 on.
_SHOWN = np.array([33 <= b <= 126 or 161 <= b <= 172 or b >= 174 for b in range(256)])
_CHAR = np.where(_SHOWN, np.arange(256), 255 + np.cumsum(~_SHOWN)).astype("<u2")


def gathered(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Places first, first + 1, ... of runs of n, one run behind the other."""
    ends = np.cumsum(n)
    return np.repeat(first - (ends - n), n) + np.arange(ends[-1] if len(ends) else 0)


class WordEncoder:
    """ids of texts, as unsigned 16-bit numbers. `keep` bounds the words remembered, not the result."""

    def __init__(self, path: str, kind: str, keep: int = 1_000_000):
        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        if self.library.get_vocab_size() > 1 << 16:
            raise ValueError("ids need more than 16 bits")
        if any("<|" not in t.content for t in self.library.get_added_tokens_decoder().values()):
            raise ValueError("added tokens that a plain text can hold")
        # The library's own model takes words that are cut and spelt in its alphabet, without the cost of an encoding each.
        self.tokens_of = self.library.model.tokenize
        self.kind, self.kinds, self.table = kind, Kinds(self.library, kind == "byte"), WordTable(keep)
        self._forget()

    def _forget(self) -> None:
        self.table.clear()
        self.first, self.n, self.pool = Grown(np.int64), Grown(np.int64), Grown(np.uint16)

    def _learn(self, raw: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> None:
        """Ids of new words, spelt all at once and told apart by a character the alphabet lacks."""
        sizes, tokens_of = ends - starts + 1, self.tokens_of
        spelt = _CHAR[raw[np.minimum(gathered(starts, sizes), len(raw) - 1)]]
        spelt[np.cumsum(sizes) - 1] = 32
        ids: list[int] = []
        counts = []
        for word in spelt.tobytes().decode("utf-16-le").split(" ")[:-1]:
            got = [t.id for t in tokens_of(word)]
            counts.append(len(got))
            ids += got
        n = np.array(counts, np.int64)
        self.first.extend(self.pool.used + np.cumsum(n) - n)
        self.n.extend(n)
        self.pool.extend(np.array(ids, np.uint16))

    def _texts(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ids before each text) of texts that need no help."""
        spaced = self.kind == "byte"
        if len(raw) and raw.max() >= 128:
            text = raw.tobytes().decode()
            if spaced:
                low = raw
            else:
                at = np.searchsorted(np.flatnonzero((raw & 0xC0) != 0x80), offsets)
                text = text.lower()
                low = np.frombuffer(text.encode(), np.uint8)
            leads = np.append(np.flatnonzero((low & 0xC0) != 0x80), len(low))
            codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
            if spaced:
                at = np.searchsorted(leads, offsets)
            offsets = leads[at]
        else:
            low = raw if spaced else _LOWER[raw]
            leads, codes, at = None, low, offsets
        starts, ends = word_spans(codes, self.kinds.of(codes), at[:-1], spaced)
        if leads is not None:
            starts, ends = leads[starts], leads[ends]
        if self.table.full:
            self._forget()
        entry, fresh = self.table.find(low, starts, ends)
        for k in range(0, len(fresh), LEARN):
            self._learn(low, starts[fresh[k : k + LEARN]], ends[fresh[k : k + LEARN]])
        n = self.n.data[entry]
        ids = self.pool.data[gathered(self.first.data[entry], n)]
        total = np.concatenate(([0], np.cumsum(n)))
        return ids, total[np.searchsorted(starts, offsets)]

    def encode_flat(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts behind each other, ids before each text)."""
        sizes = np.diff(offsets)
        alone = self._alone(raw, offsets)
        if not len(alone):
            return self._texts(raw, offsets)
        easy = np.ones(len(sizes), bool)
        easy[alone] = False
        kept = np.repeat(easy, sizes)
        ids, before = self._texts(raw[kept], np.concatenate(([0], np.cumsum(np.where(easy, sizes, 0)))))
        hard = {k: np.array(self.library.encode(raw[offsets[k] : offsets[k + 1]].tobytes().decode(), add_special_tokens=False).ids, np.uint16) for k in alone.tolist()}
        parts, at = [], 0
        n = np.diff(before)
        for k in alone.tolist():
            parts += [ids[before[at] : before[k]], hard[k]]
            n[k], at = len(hard[k]), k
        parts.append(ids[before[at] :])
        return np.concatenate(parts), np.concatenate(([0], np.cumsum(n)))

    def _alone(self, raw: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Texts that the library encodes whole."""
        odd = (raw[:-1] == ord("<")) & (raw[1:] == ord("|"))
        if self.kind == "word":
            # what case folding and composition could change in other ways than character by character
            odd = odd | _FLAG[raw[:-1]] | (raw[:-1] == 0xC2) & ((raw[1:] == 0x85) | (raw[1:] == 0xA0)) | (raw[:-1] == 0xC4) & (raw[1:] == 0xB0)
        places = np.flatnonzero(odd)
        if self.kind == "word" and len(raw) and _FLAG[raw[-1]]:
            places = np.append(places, len(raw) - 1)
        return np.unique(np.searchsorted(offsets, places, side="right") - 1)

    def encode_column(self, column) -> tuple[np.ndarray, np.ndarray]:
        """(ids, ids before each text) of an Arrow column; null is empty."""
        return self.encode_flat(*flat(column))


_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_FLAG = np.zeros(256, bool)
_FLAG[[0, *range(0x1C, 0x20)]] = True
_FLAG[0xC9:] = True  # first bytes of U+0240 and above


def encoder(path: str, kind: str) -> WordEncoder:
    """The worker's encoder; it outlives the task, and what it remembers is bounded."""
    return held(("words", path, kind), lambda: WordEncoder(path, kind))
