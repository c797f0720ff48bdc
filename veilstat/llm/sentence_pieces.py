"""SentencePiece encoding and decoding by suffix-array matching.

New text units of a batch are joined to one text. Its suffixes are sorted by their first
``longest piece`` characters (rank doubling), every piece finds its range of occurrences by
two binary searches, and the matches, sorted by position, are the edges that segmentation
relaxes over:

* unigram models: best path, position by position;
* BPE models, whose segmentation is defined by merges and not by a best path: the best
  scored edge that spans two neighbouring symbols joins them, until none does. All units
  take a merge in each round; long ones go through a queue.

Characters that no piece covers fall back to byte pieces, or to the unknown piece. A unit is
a run of spaces with the word behind it, or a line feed: no piece reaches across, so units
are encoded once and kept in a bounded worker cache.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import small_batches, texts_of, tidy

SPACE = "▁"
CACHE_UNITS = 600_000
CACHE_CHARS = 64
LONG_UNIT = 160
_UNITS = re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")


@lru_cache(maxsize=2)
def load_model(path: str) -> dict:
    """Pieces, scores, types and normaliser switches of a model file."""
    from sentencepiece import sentencepiece_model_pb2 as proto

    m = proto.ModelProto()
    with open(path, "rb") as f:
        m.ParseFromString(f.read())
    spec = m.normalizer_spec
    if spec.precompiled_charsmap:
        raise ValueError("models with a character map are not supported; normalise the text first")
    return {
        "pieces": [p.piece for p in m.pieces],
        "scores": np.array([p.score for p in m.pieces]),
        "types": np.array([p.type for p in m.pieces]),
        "bpe": m.trainer_spec.model_type == proto.TrainerSpec.BPE,
        "prefix": spec.add_dummy_prefix,
        "squeeze": spec.remove_extra_whitespaces,
    }


NORMAL, UNKNOWN, CONTROL, USER, BYTE = 1, 2, 3, 4, 6


class Segmenter(dict):
    """unit -> its ids as little-endian uint32 bytes."""

    def __init__(self, path: str):
        super().__init__()
        self.model = m = load_model(path)
        self.usable = np.flatnonzero((m["types"] == NORMAL) | (m["types"] == USER))
        self.longest = max((len(m["pieces"][i]) for i in self.usable), default=1)
        chars = sorted({c for i in self.usable for c in m["pieces"][i]})
        # Code 0 ends a unit, 1 is any character that no piece holds.
        self.code = {c: k for k, c in enumerate(chars, 2)}
        points = np.array([ord(c) for c in chars], dtype=np.uint32)
        self.points = points
        width = self.longest
        keys = np.zeros((len(self.usable), width), ">u2")
        self.lengths = np.zeros(len(self.usable), np.int64)
        for k, i in enumerate(self.usable):
            codes = [self.code[c] for c in m["pieces"][i]]
            keys[k, : len(codes)] = codes
            self.lengths[k] = len(codes)
        high = keys.copy()
        high[np.arange(width)[None, :] >= self.lengths[:, None]] = 0xFFFF
        self.low, self.high = (np.ascontiguousarray(x).view(f"V{2 * width}").ravel() for x in (keys, high))
        self.low, self.high = (np.frombuffer(x.tobytes(), f"S{2 * width}") for x in (self.low, self.high))
        self.unknown = int(np.flatnonzero(m["types"] == UNKNOWN)[0])
        self.byte = {int(p[3:5], 16): i for i, p in enumerate(m["pieces"]) if m["types"][i] == BYTE}
        self.feed_apart = "\n" not in self.code
        self.score = m["scores"].copy()

    # Matching

    def edges(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(position, piece, length) of every occurrence of every piece, sorted by position."""
        n, width = len(codes), self.longest
        rank = codes.astype(np.int64)
        step = 1
        while step < width:
            after = np.zeros(n, np.int64)
            if step < n:
                after[: n - step] = rank[step:] + 1
            _, rank = np.unique(rank * (n + 70_000) + after, return_inverse=True)
            step *= 2
        suffixes = np.argsort(rank, kind="stable")
        padded = np.zeros(n + width, ">u2")
        padded[:n] = codes
        windows = np.lib.stride_tricks.sliding_window_view(padded, width)[:n]
        keys = np.frombuffer(np.ascontiguousarray(windows[suffixes]).tobytes(), f"S{2 * width}")
        first = np.searchsorted(keys, self.low, side="left")
        count = np.searchsorted(keys, self.high, side="right") - first
        hit = np.flatnonzero(count > 0)
        count, first = count[hit], first[hit]
        inside = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        position = suffixes[np.repeat(first, count) + inside]
        piece, length = np.repeat(self.usable[hit], count), np.repeat(self.lengths[hit], count)
        order = np.argsort(position, kind="stable")
        return position[order], piece[order], length[order]

    def codes_of(self, text: str) -> np.ndarray:
        points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        at = np.searchsorted(self.points, points)
        at[at == len(self.points)] = 0
        codes = np.where(self.points[at] == points, at + 2, 1)
        codes[points == 0] = 0
        return codes.astype(np.uint16)

    # Relaxing

    def _merge(self, starts: np.ndarray, ends: np.ndarray, table: np.ndarray) -> np.ndarray:
        """Start positions of the final symbols of units [start, end), by rounds of best merges."""
        unit = np.repeat(np.arange(len(starts)), ends - starts)
        symbol = np.concatenate([np.arange(a, b) for a, b in zip(starts, ends, strict=True)]) if len(starts) else np.zeros(0, np.int64)
        finished = []
        width = table.shape[1]
        while len(symbol):
            last = np.ones(len(unit), bool)
            last[:-1] = unit[1:] != unit[:-1]
            stop = np.append(symbol[1:], 0)
            stop[last] = ends[unit[last]]
            # A pair joins a symbol with the next one of the unit.
            reach = np.append(stop[1:], 0) - symbol
            pair = ~last & (reach < width)
            piece = np.full(len(symbol), -1)
            piece[pair] = table[symbol[pair], reach[pair]]
            worth = np.where(piece >= 0, self.score[piece], -np.inf)
            head = np.flatnonzero(np.concatenate(([True], unit[1:] != unit[:-1])))
            best = np.maximum.reduceat(worth, head)
            size = np.diff(head, append=len(symbol))
            can = np.repeat(best > -np.inf, size)
            top = can & (worth == np.repeat(best, size))
            at = np.flatnonzero(top)
            at = at[np.concatenate(([True], unit[at][1:] != unit[at][:-1]))] if len(at) else at  # leftmost of ties
            finished.append(symbol[~can])
            keep = can
            keep[at + 1] = False
            symbol, unit = symbol[keep], unit[keep]
        return np.sort(np.concatenate(finished)) if finished else symbol

    def _merge_long(self, start: int, end: int, table: np.ndarray) -> list[int]:
        """The same for one long unit, by a queue of candidate merges."""
        after = {i: i + 1 for i in range(start, end)}
        before = {i: i - 1 for i in range(start, end)}
        width, queue = table.shape[1], []

        def offer(a: int) -> None:
            b = after.get(a, end)
            if b < end and (size := after[b] - a) < width and (piece := table[a, size]) >= 0:
                heapq.heappush(queue, (-self.score[piece], a, b, after[b]))

        for i in range(start, end):
            offer(i)
        while queue:
            _, a, b, stop = heapq.heappop(queue)
            if after.get(a) != b or after.get(b) != stop:
                continue
            after[a] = stop
            del after[b]
            if stop < end:
                before[stop] = a
            offer(a)
            if a > start:
                offer(before[a])
        return sorted(after)

    def _best_path(self, start: int, end: int, table: np.ndarray) -> list[int]:
        """Unigram: start positions of the pieces with the largest total score."""
        n = end - start
        best, back = np.full(n + 1, -np.inf), np.zeros(n + 1, np.int64)
        best[0] = 0.0
        lowest = self.score[self.usable].min() - 10.0
        for i in range(n):
            for size in np.flatnonzero(table[start + i, : n - i + 1] >= 0) if n - i else ():
                v = best[i] + self.score[table[start + i, size]]
                if v > best[i + size]:
                    best[i + size], back[i + size] = v, i
            if table[start + i, 1] < 0 and best[i] + lowest > best[i + 1]:
                best[i + 1], back[i + 1] = best[i] + lowest, i
        out, at = [], n
        while at:
            at = int(back[at])
            out.append(start + at)
        return out[::-1]

    def segment(self, units: list[str]) -> list[np.ndarray]:
        """Ids of units that hold no null character."""
        text = "\0".join(units) + "\0"
        codes = self.codes_of(text)
        sizes = np.array([len(u) for u in units], np.int64)
        ends = np.cumsum(sizes + 1) - 1
        starts = ends - sizes
        position, piece, length = self.edges(codes)
        small = len(self.model["pieces"]) < 1 << 15  # a row a character: the narrowest type counts
        table = np.full((len(codes), self.longest + 1), -1, np.int16 if small else np.int32)
        table[position, length] = piece
        if self.model["bpe"]:
            long = sizes > LONG_UNIT
            symbols = [self._merge(starts[~long], ends[~long], table)]
            symbols += [np.array(self._merge_long(a, b, table), np.int64) for a, b in zip(starts[long].tolist(), ends[long].tolist(), strict=True)]
        else:
            symbols = [np.array(self._best_path(a, b, table), np.int64) for a, b in zip(starts.tolist(), ends.tolist(), strict=True)]
        symbol = np.sort(np.concatenate(symbols))
        unit = np.searchsorted(ends, symbol, side="right")
        stop = np.append(symbol[1:], len(codes))
        stop = np.minimum(stop, ends[unit])
        ids = table[symbol, stop - symbol].astype(np.int64)
        missing = np.flatnonzero(ids < 0)
        if len(missing):
            parts, at = [], 0
            units_of = [unit[:0]]
            for k in missing.tolist():
                raw = text[symbol[k] : stop[k]].encode()
                other = [self.byte[b] for b in raw] if self.byte else [self.unknown]
                parts += [ids[at:k], np.array(other, np.int64)]
                units_of += [unit[at:k], np.full(len(other), unit[k])]
                at = k + 1
            ids = np.concatenate([*parts, ids[at:]])
            unit = np.concatenate([*units_of, unit[at:]])
        cuts = np.searchsorted(unit, np.arange(1, len(units)))
        return np.split(ids.astype("<u4"), cuts)

    # Texts

    def units(self, text: str) -> list[str]:
        if not text:
            return []
        if self.model["squeeze"]:
            text = re.sub(" +", " ", text.strip(" "))
        if "  " in text or text[-1:] == " " or SPACE in text or "\0" in text or not self.feed_apart or not self.model["prefix"]:
            return _UNITS.findall((SPACE if self.model["prefix"] else "") + text.replace(" ", SPACE))
        out: list[str] = []
        for k, line in enumerate(text.split("\n")):
            if k:
                out.append("\n")
            first, gap, rest = line.partition(" ")
            if k == 0:
                out.append(SPACE + first)
            elif first:
                out.append(first)
            if gap:
                out += [SPACE + w for w in rest.split(" ")]
        return out

    def learn(self, units: list[str]) -> None:
        fresh = [u for u in set(units) if u not in self and len(u) <= CACHE_CHARS and "\0" not in u]
        if len(self) + len(fresh) > CACHE_UNITS:
            keep = list(self.items())[: CACHE_UNITS // 2]
            self.clear()
            self.update(keep)
            fresh = [u for u in set(units) if u not in self and len(u) <= CACHE_CHARS and "\0" not in u]
        fresh.sort()
        for at in range(0, len(fresh), 60_000):
            some = fresh[at : at + 60_000]
            self.update(zip(some, (x.tobytes() for x in self.segment(some)), strict=True))

    def __missing__(self, unit: str) -> bytes:
        out = []
        for k, part in enumerate(unit.split("\0")):  # a null character is no piece: its byte
            if k:
                out.append(np.array([self.byte[0] if self.byte else self.unknown], "<u4"))
            if part:
                out += self.segment([part])
        return b"".join(x.tobytes() for x in out)

    def encode(self, texts: list[str]) -> list[bytes]:
        parts = [self.units(t) for t in texts]
        self.learn([u for p in parts for u in p])
        return [b"".join(map(self.__getitem__, p)) for p in parts]

    def decode(self, ids: np.ndarray) -> str:
        """Text of ids: byte pieces join to UTF-8, control pieces vanish, the dummy space goes."""
        if not hasattr(self, "_bytes"):
            m = self.model
            special = {UNKNOWN: " ⁇ ".encode(), CONTROL: b""}
            self._bytes = [bytes([int(p[3:5], 16)]) if t == BYTE else special.get(t, p.replace(SPACE, " ").encode()) for p, t in zip(m["pieces"], m["types"].tolist(), strict=True)]
        out = b"".join(map(self._bytes.__getitem__, ids.tolist())).decode("utf-8", "replace")
        return out[1:] if self.model["prefix"] and out[:1] == " " else out


def encode_documents(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_pieces, ids_crc32, decoded_sha256, round_trip for every row's whole text.

    Ids are those of the model's library without begin or end pieces; ``ids_crc32`` is over
    little-endian unsigned 32-bit ids; ``round_trip`` tells whether decoding gives the text
    (a literal U+2581 comes back as a space). A null text is an empty one without pieces.
    Rows are independent: repeated and null ids give a row each. An empty table gives an
    empty result; columns other than doc_id and text are ignored.
    """
    small_batches(docs.sparkSession)
    ids_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        seg = Segmenter(path)
        for batch in batches:
            texts = texts_of(batch.column(1)).to_pylist()
            n, crc, sha, same = [], [], [], []
            for text, raw in zip(texts, seg.encode(texts), strict=True):
                n.append(len(raw) // 4)
                crc.append(zlib.crc32(raw))
                back = seg.decode(np.frombuffer(raw, "<u4"))
                sha.append(hashlib.sha256(back.encode()).hexdigest())
                same.append(back == text)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(crc, pa.int64()), pa.array(sha, pa.string()), pa.array(same, pa.bool_())], ["doc_id", "n_pieces", "ids_crc32", "decoded_sha256", "round_trip"])
        tidy()

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {ids_type}, n_pieces long, ids_crc32 long, decoded_sha256 string, round_trip boolean")
