"""Repeated passages: fixed-block anchors, extended to maximal exact repeats.

Every document's non-overlapping blocks of ``BLOCK`` words, from its start, are the
reference index; every rolling run of ``BLOCK`` words probes it. A repeat of ``WINDOW``
words holds a whole block of either document as long as 2 * BLOCK - 1 <= WINDOW, so each
side of a repeat is hit. Hits are extended: the windows of ``WINDOW`` words that cover a hit
are compared by 96-bit hashes, and each one that also starts earlier is removed; the union
of removed windows is the maximal exact repeat.

Index, probes and windows travel in packed rows, dealt by hash. A slice of text (about
2 MB) sends a hash once at most: a run that a slice holds twice is a hit already, and of
equal windows in a slice all but the first are repeats already. So a passage that a third
of all documents share costs one entry a slice, not one a document.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, small_batches, stage, text_slices
from .packed import first_of, gaps, squeeze, unsqueeze
from .textkernel import grams, mix, words

WINDOW = 20
BLOCK = 10
#: Probes that one hash partition holds on average.
SHARE = 4_000_000

_KEYED = "d long, t long"


def _keyed(docs: DataFrame) -> DataFrame:
    """Documents with a sort key: the id (null last), then a hash of the text."""
    text = F.coalesce("text", F.lit(""))
    return only(docs, "doc_id", "text").select(F.coalesce(F.col("doc_id").cast("long"), F.lit((1 << 63) - 1)).alias("d"), F.xxhash64(text).alias("t"), text.alias("text"), "doc_id")


def _emit(p: np.ndarray, low: np.ndarray, place: np.ndarray, ids: np.ndarray, keys: np.ndarray, ends: np.ndarray, more: list[np.ndarray]):
    """Packed rows (p, blob), one for each hash partition; places are in slice order."""
    order = np.argsort(p, kind="stable")
    cuts = np.flatnonzero(np.diff(p[order])) + 1
    for part in np.split(order, cuts):
        if not len(part):
            continue
        where = place[part]
        docs, row = np.unique(np.searchsorted(ends, where, side="right"), return_inverse=True)
        start = np.where(docs > 0, ends[docs - 1], 0)
        per = np.bincount(row, minlength=len(docs)).astype(np.uint32)
        yield int(p[part[0]]), squeeze(low[part], gaps(where), ids[docs], keys[docs], start.astype(np.uint32), per, *[m[part] for m in more])


def _read(blob: bytes):
    """(low, d, t, position in document, extra arrays...) of a packed row."""
    low, gap, ids, keys, start, per, *more = unsqueeze(blob)
    where = np.cumsum(gap, dtype=np.int64)
    return low, np.repeat(ids, per), np.repeat(keys, per), where - np.repeat(start, per), *more


def _replies(d: np.ndarray, t: np.ndarray, at: np.ndarray, groups: int):
    """Packed rows (g, blob): places dealt by document to groups, each document's in a run."""
    g = (mix(d.view(np.uint64) ^ mix(t.view(np.uint64))) % np.uint64(groups)).astype(np.int64)
    order = np.lexsort((at, t, d, g))
    d, t, at, g = d[order], t[order], at[order].astype(np.uint32), g[order]
    for part in np.split(np.arange(len(g)), np.flatnonzero(np.diff(g)) + 1):
        if len(part):
            x = slice(part[0], part[-1] + 1)
            head = np.flatnonzero(np.concatenate(([True], (np.diff(d[x]) != 0) | (np.diff(t[x]) != 0))))
            yield int(g[part[0]]), squeeze(d[x][head], t[x][head], np.diff(head, append=len(part)).astype(np.uint32), at[x])


def _assemble(batches):
    """One row (d, t, at) for each document from the packed rows of its group."""
    held: dict[int, list] = {}
    for batch in batches:
        for g, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            held.setdefault(g, []).append(raw)
    while held:
        cols = []
        for raw in held.popitem()[1]:
            d, t, per, at = unsqueeze(raw)
            cols.append((np.repeat(d, per), np.repeat(t, per), at))
        d, t, at = (np.concatenate(c) for c in zip(*cols, strict=True))
        order = np.lexsort((at, t, d))
        d, t, at = d[order], t[order], at[order].astype("<u4")
        cuts = np.flatnonzero((np.diff(d) != 0) | (np.diff(t) != 0)) + 1
        head = np.concatenate(([0], cuts))
        for a in range(0, len(head), 2000):
            some = head[a : a + 2000]
            stops = np.append(head[a + 1 : a + 2001], len(d))[: len(some)]
            yield pa.RecordBatch.from_arrays([pa.array(d[some]), pa.array(t[some]), pa.array([at[x:y].tobytes() for x, y in zip(some.tolist(), stops.tolist(), strict=True)], pa.binary())], ["d", "t", "at"])


def _slice_keys(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    return part.column(0).to_numpy(), part.column(1).to_numpy()


_SENT = ["p", "g", "blob"]
_SENT_SCHEMA = "p int, g int, blob binary"


def _rows(sent: list[tuple], known: list[tuple]):
    """Packed rows to look at (g is -1), and packed replies that ride along."""
    return pa.RecordBatch.from_arrays(
        [
            pa.array([p for p, _ in sent] + [g for g, _ in known], pa.int32()),
            pa.array([-1] * len(sent) + [g for g, _ in known], pa.int32()),
            pa.array([b for _, b in sent] + [b for _, b in known], pa.binary()),
        ],
        _SENT,
    )


def _probe(parts: int, block: int):
    def run(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                d, t = _slice_keys(part)
                row, _, _, h = words(data, offs)
                counts = np.bincount(row, minlength=len(d))
                ends = np.cumsum(counts)
                at, g = grams(row, h, block)
                if not len(at):
                    continue
                order, starts = first_of(g)
                size = np.diff(starts, append=len(order))
                twice = np.repeat(size > 1, size)
                first_at = np.sort(order[starts])  # one of each hash, in slice order
                places = at[first_at]
                base = ends - counts
                aligned = ((places - base[row[places]]) % block == 0).astype(np.uint8)
                shared = np.zeros(len(order), np.uint8)
                shared[order[twice]] = 1
                # A hash met twice is known to repeat; it may stand for a block of any of its places.
                flag = aligned | shared[first_at]
                hashed = g[first_at]
                sent = list(_emit((hashed >> np.uint64(32)).astype(np.int64) % parts, hashed.astype(np.uint32), places, d, t, ends, [flag]))
                known = np.sort(at[order[twice]])
                yield _rows(sent, list(_replies(d[row[known]], t[row[known]], known - base[row[known]], parts)))

    return run


def _gather(decide, parts: int):
    """Decode a partition's rows by p, pass replies on, and reply with what ``decide`` finds."""

    def run(batches):
        held: dict[int, list] = {}
        for batch in batches:
            done = batch.filter(pc.greater_equal(batch.column(1), 0))
            if done.num_rows:
                yield pa.RecordBatch.from_arrays(done.columns[1:], ["g", "blob"])
            for p, g, raw in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if g < 0:
                    held.setdefault(p, []).append(raw)
        while held:
            _, blobs = held.popitem()
            out = list(_replies(*decide([np.concatenate(c) for c in zip(*map(_read, blobs), strict=True)]), parts))
            yield pa.RecordBatch.from_arrays([pa.array([g for g, _ in out], pa.int32()), pa.array([b for _, b in out], pa.binary())], ["g", "blob"])

    return run


def _hit(columns):
    """Places whose hash stands at two places at least, one of them a reference block."""
    low, d, t, at, flag = columns
    order, starts = first_of(low)
    size = np.diff(starts, append=len(order))
    some = np.add.reduceat(flag[order], starts, dtype=np.int64) if len(starts) else starts
    chosen = order[np.repeat((size > 1) & (some > 0), size)]
    return d[chosen], t[chosen], at[chosen]


def _windows(parts: int, window: int, block: int):
    """Windows around hits: within a slice later equals are repeats, firsts are sent."""

    def run(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                d, t = _slice_keys(part)
                hits = part.column(3).to_pylist()
                row, _, _, h = words(data, offs)
                counts = np.bincount(row, minlength=len(d))
                ends = np.cumsum(counts)
                base = ends - counts
                near = np.zeros(len(row) + 1, dtype=np.int64)
                for i, raw in enumerate(hits):
                    got = np.frombuffer(raw, "<u4").astype(np.int64)
                    np.add.at(near, base[i] + np.maximum(got - (window - block), 0), 1)
                    np.add.at(near, base[i] + got + 1, -1)
                at, g = grams(row, h, window)
                wanted = np.cumsum(near)[at] > 0
                at, g = at[wanted], g[wanted]
                if not len(at):
                    continue
                second = mix(grams(row, mix(h + np.uint64(99)), window)[1][wanted]).astype(np.uint32)
                r = row[at]
                pos = at - base[r]
                by = np.lexsort((pos, t[r], d[r], second, g))
                new = np.ones(len(by), bool)
                new[1:] = (g[by][1:] != g[by][:-1]) | (second[by][1:] != second[by][:-1])
                lead = np.maximum.accumulate(np.where(new, np.arange(len(by)), 0))
                x, y = by, by[lead]
                later = (d[r[x]] != d[r[y]]) | (t[r[x]] != t[r[y]]) | (pos[x] != pos[y])
                rest = x[~new & later]
                send = np.sort(by[new])
                sent = list(_emit((g[send] >> np.uint64(32)).astype(np.int64) % parts, g[send], at[send], d, t, ends, [second[send]]))
                yield _rows(sent, list(_replies(d[r[rest]], t[r[rest]], pos[rest], parts)))

    return run


def _repeat(columns):
    """Places of windows that stand earlier, too."""
    g, d, t, at, second = columns
    order = np.lexsort((at, t, d, second, g))
    g, d, t, at, second = g[order], d[order], t[order], at[order], second[order]
    new = np.ones(len(g), bool)
    new[1:] = (g[1:] != g[:-1]) | (second[1:] != second[:-1])
    lead = np.maximum.accumulate(np.where(new, np.arange(len(g)), 0)) if len(g) else np.zeros(0, int)
    later = (d != d[lead]) | (t != t[lead]) | (at != at[lead])
    return d[later], t[later], at[later]


def _answer(sent: DataFrame, decide, parts: int) -> DataFrame:
    """(d, t, at): the places that ``decide`` picks, one row for each document."""
    replies = sent.repartition(parts, "p").mapInArrow(_gather(decide, parts), "g int, blob binary")
    return replies.repartition(parts, "g").mapInArrow(_assemble, "d long, t long, at binary")


def repeats(docs: DataFrame, window: int = WINDOW, block: int = BLOCK) -> tuple[DataFrame, DataFrame]:
    """(touched documents with their texts, (d, t, at): starts of windows that stand earlier, too)."""
    if 2 * block - 1 > window:
        raise ValueError("a window must hold a whole block: 2 * block - 1 <= window")
    spark = docs.sparkSession
    small_batches(spark)
    keyed = _keyed(docs)
    total = keyed.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(1, -(-total // (6 * SHARE)))
    run = _probe(parts, block)
    probes = keyed.select("d", "t", "text").mapInArrow(run, _SENT_SCHEMA)
    hits = stage(_answer(probes, _hit, parts), "hits")
    touched = stage(keyed.select("d", "t", "text").join(hits.hint("shuffle_hash"), ["d", "t"]), "touched")
    run = _windows(parts, window, block)
    sent = touched.select("d", "t", "text", "at").mapInArrow(run, _SENT_SCHEMA)
    return touched, stage(_answer(sent, _repeat, parts).withColumnRenamed("at", "starts"), "repeats")


_TRIM = dict(n_words="long", n_removed="long", kept_sha256="string", kept_text="string")


def _trim(window: int, with_text: bool):
    names = ["n_words", "n_removed", "kept_sha256", *(["kept_text"] if with_text else [])]

    def run(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                row, s, e, _ = words(data, offs, hashes=False)
                counts = np.bincount(row, minlength=part.num_rows)
                base = np.cumsum(counts) - counts
                raw = data.tobytes()
                starts = part.column(3).to_pylist()
                n_removed, sha, texts = [], [], []
                for i in range(part.num_rows):
                    a, b = base[i], base[i] + counts[i]
                    keep = np.ones(counts[i], bool)
                    if starts[i]:
                        cover = np.zeros(counts[i] + 1, np.int64)
                        got = np.unique(np.frombuffer(starts[i], "<u4")).astype(np.int64)
                        cover[got] += 1
                        np.add.at(cover, np.minimum(got + window, counts[i]), -1)
                        keep = np.cumsum(cover[:-1]) == 0
                    kept = b" ".join([raw[x:y] for x, y in zip(s[a:b][keep].tolist(), e[a:b][keep].tolist(), strict=True)])
                    n_removed.append(int(counts[i] - keep.sum()))
                    sha.append(hashlib.sha256(kept).hexdigest())
                    texts.append(kept.decode() if with_text else "")
                arrays = [pa.array(counts), pa.array(n_removed, pa.int64()), pa.array(sha, pa.string()), *([pa.array(texts, pa.string())] if with_text else [])]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *arrays], ["d", "t", *names])

    return run, f"{_KEYED}, " + ", ".join(f"{n} {_TRIM[n]}" for n in names)


def remove_repeats(docs: DataFrame, window: int = WINDOW, block: int = BLOCK, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and kept_text) for every row.

    Words are runs without ASCII white space; a null text has none. A word goes when a
    window of ``window`` words covers it that also starts earlier: in a smaller doc_id or
    before it in the same document. Null ids rank last; rows that repeat an id rank by a
    hash of their text, and rows equal in id and text count as one place, so neither goes.
    An empty table gives an empty result; other columns are ignored.
    """
    touched, found = repeats(docs, window, block)
    run, schema = _trim(window, with_text)
    trimmed = touched.select("d", "t", "text").join(found.hint("shuffle_hash"), ["d", "t"]).select("d", "t", "text", "starts").mapInArrow(run, schema).dropDuplicates(["d", "t"])
    keyed = _keyed(docs)
    plain = keyed.select("d", "t", "text", F.lit(None).cast("binary").alias("starts"), "doc_id")
    ids = docs.schema["doc_id"].dataType.simpleString()

    def whole(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                row = words(data, offs, hashes=False)[0]
                counts = np.bincount(row, minlength=part.num_rows)
                raw, sha, texts = data.tobytes(), [], []
                for i in range(part.num_rows):
                    kept = b" ".join(raw[offs[i] : offs[i + 1]].split())  # bytes split at ASCII white space alone
                    sha.append(hashlib.sha256(kept).hexdigest())
                    texts.append(kept.decode() if with_text else "")
                arrays = [pa.array(counts), pa.array(sha, pa.string()), *([pa.array(texts, pa.string())] if with_text else [])]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), part.column(4), *arrays], ["d", "t", "doc_id", "n", "sha", *(["txt"] if with_text else [])])

    full = plain.mapInArrow(whole, f"{_KEYED}, doc_id {ids}, n long, sha string" + (", txt string" if with_text else ""))
    out = full.join(trimmed, ["d", "t"], "left")
    cols = ["doc_id", F.col("n").alias("n_words"), F.coalesce("n_removed", F.lit(0)).cast("long").alias("n_removed"), F.coalesce("kept_sha256", "sha").alias("kept_sha256")]
    return out.select(*cols, *([F.coalesce("kept_text", "txt").alias("kept_text")] if with_text else []))

