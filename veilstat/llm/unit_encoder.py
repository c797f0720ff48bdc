"""Token ids of whole texts from a compact table of text units, in vectorised steps.

A text is cut into units at places where the tokenizer's own rule always starts a new
pre-token, so the units' ids put together are the ids of the text:

* ``word`` (word-level BPE, white space dropped, lower case): runs without ASCII white
  space; a last ``. , ; :`` behind a letter is a unit of its own.
* ``byte`` (byte-level BPE): the same with a single space before it, as "␣word" is one
  pre-token; of a longer run of white space all but the last character are one unit.

Units are found and hashed over raw bytes, looked up in sorted arrays, and the ids are
gathered from a pool. A hash counts only with the unit's length and first bytes. Units that
the table lacks are encoded together and kept; on overflow the half that came first, in
which the frequent units are, stays. Texts beyond these rules (white space outside ASCII, or
special strings, in byte style) go to the tokenizer whole.
"""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np

from .common import slices
from .textkernel import _IS_WORD, _LOWER, _STEP, _places, mix, stream

#: Units kept by a worker.
UNITS = 1_000_000
RECENT = 120_000
#: Bytes of text that are looked up at once.
SLICE = 1 << 20

_ALL = stream(256, 11)
_WORD_ONLY = _ALL.copy()
_WORD_ONLY[~_IS_WORD] = 0
_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123)]] = True
_LATIN_TAIL = np.zeros(256, bool)
_LATIN_TAIL[[b for b in range(0x80, 0xC0) if b not in (0x97, 0xB7)]] = True
_STOP = np.zeros(256, bool)
_STOP[[ord(c) for c in ".,;:"]] = True
#: UTF-8 of white space outside ASCII.
_WIDE_SPACE = re.compile(b"\xc2[\x85\xa0]|\xe1\x9a\x80|\xe2\x80[\x80-\x8a\xa8\xa9\xaf]|\xe2\x81\x9f|\xe3\x80\x80")
_LEAD = np.zeros(256, bool)
_LEAD[[0xC2, 0xE1, 0xE2, 0xE3]] = True


@lru_cache(maxsize=4)
def load(path: str):
    """The tokenizer, once per Python worker, single-threaded."""
    import os

    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(path)
    tok.no_padding()
    tok.no_truncation()
    return tok


def latin(word: str) -> bool:
    """Letters for which neither NFC nor lower-casing can open a second pre-token."""
    return word.isalpha() and (word.isascii() or (max(word) < "ɐ" and "İ" not in word))


def spans(data: np.ndarray, offs: np.ndarray, style: str) -> tuple[np.ndarray, np.ndarray]:
    """(start, end) of every unit, ascending; in byte style they cover every byte."""
    n = len(data)
    inside = _IS_WORD[data]
    starts, ends = inside.copy(), inside.copy()
    starts[1:] &= ~inside[:-1]
    ends[:-1] &= ~inside[1:]
    first = offs[:-1][offs[:-1] < n]
    last = offs[1:][offs[1:] > 0] - 1
    starts[first] = inside[first]
    ends[last] = inside[last]
    s, e = np.flatnonzero(starts), np.flatnonzero(ends) + 1
    # A last stop behind a letter: cut before it.
    size = e - s
    tail = (size > 1) & _STOP[data[e - 1]]
    prev = data[e - 2]
    letter = _LETTER[prev]
    if (prev > 127).any():
        letter |= (size > 2) & _LATIN_TAIL[prev] & (data[np.maximum(e - 3, 0)] == 0xC3)
    tail &= letter
    cut = e[tail] - 1
    if style == "word":
        at = np.concatenate((s, cut))
        stop = np.concatenate((np.where(tail, e - 1, e), e[tail]))
        order = np.argsort(at, kind="stable")
        return at[order], stop[order]
    # Byte style: mark every unit's first byte.
    mark = np.zeros(n, bool)
    mark[first] = True
    mark[cut] = True
    before = s - 1
    spaced = (s > 0) & ~mark[s]  # not the first byte of a row
    space = spaced & (data[before] == 32)
    mark[np.where(space, before, s)] = True
    # White space opens a unit behind a word, and its last character does where a word follows.
    blank = ~inside
    opens = blank.copy()
    opens[1:] &= inside[:-1]
    mark |= opens
    behind = before[spaced]
    mark[behind] = True
    at = np.flatnonzero(mark)
    return at, np.append(at[1:], n)


class UnitEncoder:
    """``frequent``: (keys, checks, lengths) of a first tier that counts only, sorted by key."""

    def __init__(self, path: str, style: str, counts_only: bool = False, frequent=None):
        self.tok, self.style, self.counts_only = load(path), style, counts_only
        vocab = self.tok.get_vocab()
        self.edge = np.zeros(max(vocab.values()) + 1, dtype=bool)
        for token, i in vocab.items():
            self.edge[i] = token.endswith("</w>") if style == "word" else token.startswith("Ġ")
        self.feed = vocab.get("Ċ", -1)
        self.special = [t.content.encode() for t in self.tok.get_added_tokens_decoder().values()]
        self.value = _WORD_ONLY if style == "word" else _ALL
        empty = (np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64))
        self.tables = [empty, empty]
        if frequent is not None:
            keys, checks, lengths = frequent
            self.tables.append((keys, checks, np.zeros(len(keys), np.int64), lengths))
        self.pool, self.used = np.zeros(1 << 16, "<u4"), 0

    # Encoding new units

    def _plain(self, text: str) -> np.ndarray:
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, dtype="<u4")

    def _together(self, stems: list[str], between: str) -> list[np.ndarray] | tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids, starts, ends) of stems encoded as one text; ``between`` is dropped, empty, or a token of its own."""
        ids = np.array(self.tok.encode_batch_fast([between.join(stems)], add_special_tokens=False)[0].ids, dtype="<u4")
        if between == "\n":
            at = np.flatnonzero(ids == self.feed)
            starts, ends = np.append(0, at + 1), np.append(at, len(ids))
        elif self.style == "word":
            ends = np.flatnonzero(self.edge[ids]) + 1
            starts = np.append(0, ends[:-1])
        else:
            starts = np.flatnonzero(self.edge[ids])
            ends = np.append(starts[1:], len(ids))
        if len(starts) != len(stems):  # a vocabulary with other word marks: one by one
            each = [self._plain(s) for s in stems]
            ends = np.cumsum([len(x) for x in each])
            ids, starts = np.concatenate(each), np.append(0, ends[:-1])
        return ids, starts, ends

    def _encode_units(self, units: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids end to end, lengths) in the order of ``units``."""
        groups: dict[str, list[int]] = {" ": [], "": [], "\n": [], "one": []}
        for k, u in enumerate(units):
            if self.style == "word":
                groups[" " if latin(u) else "one"].append(k)
            elif u[:1] == " " and u[1:].isalpha():
                groups[""].append(k)
            else:
                groups["\n" if u.isalpha() else "one"].append(k)
        lengths, starts = np.zeros(len(units), np.int64), np.zeros(len(units), np.int64)
        parts, total = [], 0
        for between, members in groups.items():
            if not members:
                continue
            if between == "one":
                each = [self._plain(units[k]) for k in members]
                size = np.array([len(x) for x in each])
                ids, a = np.concatenate(each), np.cumsum(size) - size
            else:
                ids, a, b = self._together([units[k] for k in members], between)
                size = b - a
            starts[members], lengths[members] = a + total, size
            parts.append(ids)
            total += len(ids)
        flat = np.concatenate(parts)
        return flat[np.repeat(starts - (np.cumsum(lengths) - lengths), lengths) + np.arange(lengths.sum())], lengths

    def _learn(self, keys: np.ndarray, checks: np.ndarray, units: list[str]) -> None:
        ids, lengths = self._encode_units(units)
        if len(self.tables[0][0]) + len(self.tables[1][0]) + len(keys) > UNITS:
            self._shrink()
        at = np.zeros(len(keys), np.int64)
        if not self.counts_only:
            while self.used + len(ids) > len(self.pool):
                self.pool = np.concatenate((self.pool, np.zeros(len(self.pool), "<u4")))
            self.pool[self.used : self.used + len(ids)] = ids
            at = self.used + np.cumsum(lengths) - lengths
            self.used += len(ids)
        else:
            at += self.used
            self.used += 1
        self.tables[1] = self._merged(self.tables[1], (keys, checks, at, lengths))
        if len(self.tables[1][0]) > RECENT:
            self.tables[0] = self._merged(self.tables[0], self.tables[1])
            self.tables[1] = tuple(x[:0] for x in self.tables[1])

    @staticmethod
    def _merged(a, b):
        both = [np.concatenate(x) for x in zip(a, b, strict=True)]
        order = np.argsort(both[0], kind="stable")
        return tuple(x[order] for x in both)

    def _shrink(self) -> None:
        table = self._merged(self.tables[0], self.tables[1])
        if not len(table[0]):
            return
        keep = table[2] <= np.partition(table[2], len(table[2]) // 2)[len(table[2]) // 2]
        self.tables[0] = tuple(x[keep] for x in table)
        self.tables[1] = tuple(x[:0] for x in table)
        if not self.counts_only:
            self.used = int((self.tables[0][2] + self.tables[0][3]).max())

    # Looking up

    def _find(self, keys: np.ndarray, checks: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(known, clash, at, lengths) of distinct keys."""
        known, clash = np.zeros(len(keys), bool), np.zeros(len(keys), bool)
        at, lengths = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        for table in self.tables:
            if not len(table[0]):
                continue
            k = np.searchsorted(table[0], keys)
            k[k == len(table[0])] = 0
            hit = (table[0][k] == keys) & ~known
            same = table[1][k] == checks
            clash |= hit & ~same
            hit &= same
            known |= hit
            at[hit], lengths[hit] = table[2][k[hit]], table[3][k[hit]]
        return known, clash & ~known, at, lengths

    def _hash(self, data: np.ndarray, s: np.ndarray, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n, base = len(data), s[0]
        gap = np.diff(s, append=n)
        place = np.arange(base, n) - np.repeat(s, gap)
        size = (e - s).astype(np.uint64)
        h = mix(np.add.reduceat(self.value[data[base:]] * _places(int(gap.max()))[place], s - base) + size * _STEP)
        padded = np.concatenate((data, np.zeros(8, np.uint8)))
        head = np.lib.stride_tricks.sliding_window_view(padded, 8)[s].copy().view("<u8").ravel()
        short = size < 8
        head[short] &= (np.uint64(1) << (size[short] * np.uint64(8))) - np.uint64(1)
        return h, head ^ (size << np.uint64(40))

    def _odd_rows(self, data: np.ndarray, offs: np.ndarray) -> np.ndarray:
        """Rows that the unit rules do not cover."""
        odd = np.zeros(len(offs) - 1, bool)
        if self.style == "word":
            return odd
        raw = None
        if _LEAD[data].any():
            raw = data.tobytes()
            for m in _WIDE_SPACE.finditer(raw):
                odd[np.searchsorted(offs, m.start(), side="right") - 1] = True
        if (data == 124).any():
            raw = raw or data.tobytes()
            for token in self.special:
                at = raw.find(token)
                while at >= 0:
                    odd[np.searchsorted(offs, at, side="right") - 1] = True
                    at = raw.find(token, at + 1)
        return odd

    def encode(self, data: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all rows end to end, ids of each row); without ids where only counts are kept."""
        rows = len(offs) - 1
        odd = self._odd_rows(data, offs)
        counts, gather = np.zeros(rows, np.int64), None
        if len(data):
            plain = _LOWER[data] if self.style == "word" and not self._marked(data) else data
            s, e = spans(data, offs, self.style)
            if len(s):
                row = np.searchsorted(offs[1:], s, side="right")
                h, check = self._hash(plain, s, e)
                order = np.argsort(h)
                v = h[order]
                new = np.concatenate(([True], v[1:] != v[:-1]))
                which = np.empty(len(h), np.int64)
                which[order] = np.cumsum(new) - 1
                first = order[new]
                keys, checks = h[first], check[first]
                twisted = checks[which] != check  # two units of one hash in this slice
                known, clash, at, lengths = self._find(keys, checks)
                fresh = np.flatnonzero(~known & ~clash)
                if len(fresh):
                    raw = plain.tobytes()
                    units = [raw[a:b].decode() for a, b in zip(s[first[fresh]].tolist(), e[first[fresh]].tolist(), strict=True)]
                    self._learn(keys[fresh], checks[fresh], units)
                    known, clash, at, lengths = self._find(keys, checks)
                odd[row[twisted | clash[which] | ~known[which]]] = True
                each = lengths[which]
                counts = np.bincount(row, weights=each, minlength=rows).astype(np.int64)
                if not self.counts_only:
                    ends = np.cumsum(each)
                    gather = self.pool[np.repeat(at[which] - (ends - each), each) + np.arange(ends[-1] if len(ends) else 0)]
        ids = np.zeros(0, "<u4") if gather is None else gather
        if odd.any():
            cuts, parts = np.cumsum(counts), []
            for i in np.flatnonzero(odd).tolist():
                whole = self._plain(data[offs[i] : offs[i + 1]].tobytes().decode())
                parts.append((i, whole))
            if self.counts_only:
                for i, whole in parts:
                    counts[i] = len(whole)
            else:
                pieces = np.split(ids, cuts[:-1])
                for i, whole in parts:
                    pieces[i], counts[i] = whole, len(whole)
                ids = np.concatenate(pieces)
        return ids, counts

    def encode_rows(self, data: np.ndarray, offs: np.ndarray):
        """(first row, ids of some rows end to end, ids of each of them), slice by slice."""
        for a, b in slices(offs, SLICE):
            yield a, *self.encode(data[offs[a] : offs[b]], offs[a : b + 1] - offs[a])

    def weigh(self, data: np.ndarray, offs: np.ndarray, least: int = 2, most: int = 4096) -> list[tuple[bytes, int]]:
        """The heaviest units of a slice with their counts."""
        if not len(data):
            return []
        plain = _LOWER[data] if self.style == "word" and not self._marked(data) else data
        s, e = spans(data, offs, self.style)
        if not len(s):
            return []
        h, _ = self._hash(plain, s, e)
        order = np.argsort(h)
        v = h[order]
        head = np.flatnonzero(np.concatenate(([True], v[1:] != v[:-1])))
        n = np.diff(head, append=len(v))
        top = np.flatnonzero(n >= least)
        if len(top) > most:
            top = top[np.argpartition(-n[top], most)[:most]]
        raw = plain.tobytes()
        first = order[head[top]]
        return [(raw[a:b], int(k)) for a, b, k in zip(s[first].tolist(), e[first].tolist(), n[top].tolist(), strict=True)]

    def known_units(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(keys, checks, lengths) of what has been met so far, sorted: a first tier for other encoders."""
        keys, checks, _, lengths = self._merged(self.tables[0], self.tables[1])
        return keys, checks, lengths

    def _marked(self, data: np.ndarray) -> bool:
        """Whether a special string of other case could be in the text."""
        at = np.flatnonzero(data[:-1] == 60)
        return bool((data[at + 1] == 124).any())
