"""N-gram Jaccard join by vertical partitioning of the global n-gram order.

The global order ranks n-grams by the class of their document frequency (a counting sketch
of all documents; its errors change the order, not the result), then by hash. It is cut into
fragments of equal mass.

1. Equal sets fold into one (128-bit sum of its hashes and the size); a group of copies is
   one set from here on.
2. The first n-grams of a set, of which every partner must hold some, are dealt by hash.
   N-grams of few sets propose their pairs, checked by size and place; n-grams of many sets
   hand on their sets.
3. Sets that may link meet in tiles, two sides of about a thousand sets at most. A tile first
   compares parity bitmaps of the sets: every n-gram in one set only flips one bit, so the
   bits that differ bound the overlap from above, and no link is lost.
4. What is left of a tile is counted fragment by fragment, in different tasks, each of which
   gets its range of the sets once; the partial counts are summed for each pair of the tile.
   A tile answers with a forest of its links.
5. Proposed pairs and a few leaders of each large group are met first, and components join.
   Then all sets that share an n-gram but not a component meet, block against block: the
   rows of a large group of near copies grow with its blocks, not with its pairs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import drop_staged, only, sized, small_batches, stage, staged_tables, text_slices, tidy
from .components import components
from .packed import squeeze, unsqueeze
from .textkernel import grams, mix, stream, words

#: Cells of the counting sketch, a byte each: 16 MB in a worker and broadcast, whatever the corpus.
SKETCH_BITS = 24
SKETCH = 1 << SKETCH_BITS
_CELL = np.uint64(64 - SKETCH_BITS)
FRAGMENTS = 4
#: First n-grams that one hash partition holds on average.
SHARE = 1_000_000
#: Sets of an n-gram up to which it proposes pairs; those of more meet in tiles.
FEW = 16
#: Sets of a tile's side, and n-grams that they hold together (a longer set stands alone).
SIDE, SIDE_GRAMS = 1024, 1 << 20
#: Sets that lead a group in the first turn, for each band of sizes.
LEADERS = 3
#: Blocks of an n-gram's sets beyond which the n-gram has blocks of its own.
BLOCKS = 32
#: Bits of a bitmap at most.
MOST_BITS = 1 << 18


class Sets:
    """Distinct n-gram hashes of each row of a slice, sorted by row and global order."""

    def __init__(self, data: np.ndarray, offs: np.ndarray, k: int, classes: np.ndarray | None = None):
        rows = len(offs) - 1
        row, _, _, h = words(data, offs, lower=True)
        counts = np.bincount(row, minlength=rows)
        at, g = grams(row, h, k)
        r = row[at]
        few = np.flatnonzero((counts > 0) & (counts < k))
        if len(few):  # shorter texts: the whole sequence is one n-gram
            base = np.cumsum(counts) - counts
            whole = [mix(np.array([np.uint64(int(counts[i]))]) + (mix(h[base[i] : base[i] + counts[i]]) * stream(int(counts[i]), 51)).sum(dtype=np.uint64))[0] for i in few]
            r, g = np.concatenate((r, few)), np.concatenate((g, np.array(whole, np.uint64)))
        if classes is None:
            order = np.lexsort((g, r))
        else:
            order = np.lexsort((g, classes[(g >> _CELL).astype(np.int64)], r))
        r, g = r[order], g[order]
        new = np.ones(len(r), bool)
        new[1:] = (r[1:] != r[:-1]) | (g[1:] != g[:-1])
        self.row, self.gram = r[new], g[new]
        self.n = np.bincount(self.row, minlength=rows)
        self.start = np.cumsum(self.n) - self.n

    def ids(self) -> tuple[np.ndarray, np.ndarray]:
        """Two 64-bit sums over each row's set; zero for empty rows."""
        out = []
        for salt in (71, 73):
            total = np.zeros(len(self.n), np.uint64)
            if len(self.gram):
                some = self.n > 0
                total[some] = np.add.reduceat(mix(self.gram + np.uint64(salt)), self.start[some])
            out.append(mix(total + self.n.astype(np.uint64)))
        return tuple(out)

    def homes(self) -> np.ndarray:
        """The least mixed hash of each row's set, which near copies mostly share."""
        out = np.zeros(len(self.n), np.uint64)
        if len(self.gram):
            some = self.n > 0
            out[some] = np.minimum.reduceat(mix(self.gram), self.start[some])
        return out

    def bitmaps(self) -> list[bytes]:
        """For each row the parity of its n-grams over 4 to 8 bits an n-gram, a power of two of them."""
        out = []
        key = mix(self.gram ^ np.uint64(97))
        for start, n in zip(self.start.tolist(), self.n.tolist(), strict=True):
            bits = min(MOST_BITS, max(64, 1 << (4 * n - 1).bit_length())) if n else 64
            odd = np.bincount((key[start : start + n] & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
            out.append(np.packbits(odd.astype(np.uint8), bitorder="little").tobytes())
        return out


def _sid(hi: np.ndarray, lo: np.ndarray) -> list[bytes]:
    both = np.stack((hi.astype(">u8"), lo.astype(">u8")), axis=1).tobytes()
    return [both[i : i + 16] for i in range(0, len(both), 16)]


def _least(n: np.ndarray, percent: int) -> np.ndarray:
    """Least overlap that a set of n needs with any partner: ceil(percent * n / 100)."""
    return -(-percent * n // 100)


def _need(n: np.ndarray, m: np.ndarray, percent: int) -> np.ndarray:
    """Overlap that sets of n and m need."""
    return -(-percent * (n + m) // (100 + percent))


def _describe(k: int, sketch: int):
    def run(batches):
        counts = np.zeros(sketch, np.uint8)
        kind = None
        for batch in batches:
            kind = batch.schema.field(0).type
            for part, data, offs in text_slices(batch):
                sets = Sets(data, offs, k)
                cells, n = np.unique((sets.gram >> _CELL).astype(np.int64), return_counts=True)
                counts[cells] = np.minimum(counts[cells] + n, 255).astype(np.uint8)
                hi, lo = sets.ids()
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(sets.n, pa.int64()), pa.array(_sid(hi, lo), pa.binary()), pa.nulls(len(sets.n), pa.binary())], names)
        if kind is not None:
            yield pa.RecordBatch.from_arrays([pa.nulls(1, kind), pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.array([zstandard.compress(counts.tobytes(), 1)])], names)
        tidy()

    names = ["doc_id", "key", "n", "sid", "sketch"]
    return run


def _add_sketches(batches):
    total = None
    for batch in batches:
        for raw in batch.column(0).to_pylist():
            one = np.frombuffer(zstandard.decompress(raw), np.uint8)
            total = one.copy() if total is None else np.maximum(total, np.where(one > 255 - total, 255, total + one)).astype(np.uint8)
    if total is not None:
        yield pa.RecordBatch.from_arrays([pa.array([zstandard.compress(total.tobytes(), 1)])], ["sketch"])


def global_order(sketches: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """log2 class of each sketch cell, up to 8, and the places that cut the order into fragments.

    Counts saturate at 255 and are summed in two levels. Fragments hold equal shares of the
    n-grams as far as the sketch tells.
    """
    counts = np.zeros(SKETCH, np.uint8)
    tasks = sketches.count()
    if tasks:
        some = sketches.repartition(max(1, int(tasks**0.5))).mapInArrow(_add_sketches, "sketch binary")
        raw = some.coalesce(1).mapInArrow(_add_sketches, "sketch binary").first()[0]
        counts = np.frombuffer(zstandard.decompress(raw), np.uint8)
    of_count = np.ceil(np.log2(np.arange(256) + 1)).astype(np.uint8)
    classes = of_count[counts]
    cells = sum(np.bincount(counts[at : at + (1 << 20)], minlength=256) for at in range(0, SKETCH, 1 << 20))  # by slices, as counting widens them
    mass = np.cumsum(np.bincount(of_count, weights=cells * np.arange(256), minlength=9))
    cuts = []
    for f in range(1, FRAGMENTS):
        goal = mass[-1] * f / FRAGMENTS
        c = int(np.searchsorted(mass, goal))
        before = mass[c - 1] if c else 0.0
        within = (goal - before) / (mass[c] - before) if mass[c] > before else 0.0
        cuts.append((c << 56) + int(within * (1 << 56)))
    return classes, np.array(cuts, np.uint64)


def place_in_order(gram: np.ndarray, classes: np.ndarray) -> np.ndarray:
    """Class and leading hash bits of n-grams, which order as the global order does."""
    return (classes[(gram >> _CELL).astype(np.int64)].astype(np.uint64) << np.uint64(56)) | (gram >> np.uint64(8))


def _prefixes(k: int, percent: int, parts: int, order):
    """The first n-grams of every set, packed by hash partition."""

    def run(batches):
        for batch in batches:
            for _, data, offs in text_slices(batch):
                sets = Sets(data, offs, k, order.value[0])
                hi, lo = sets.ids()
                home = sets.homes()
                _, first = np.unique(hi ^ (lo * np.uint64(3)), return_index=True)  # copies in a slice once
                chosen = np.zeros(len(hi), bool)
                chosen[first] = True
                chosen &= sets.n > 0
                place = np.arange(len(sets.gram)) - sets.start[sets.row]
                keep = chosen[sets.row] & (place <= sets.n[sets.row] - _least(sets.n, percent)[sets.row])
                g, r, place = sets.gram[keep], sets.row[keep], place[keep].astype(np.uint32)
                if not len(g):
                    continue
                p = (mix(g) % np.uint64(parts)).astype(np.int64)
                by = np.argsort(p, kind="stable")
                blobs, ps = [], []
                for part_of in np.split(by, np.flatnonzero(np.diff(p[by])) + 1):
                    who, index = np.unique(r[part_of], return_inverse=True)
                    ps.append(int(p[part_of[0]]))
                    blobs.append(squeeze(g[part_of], place[part_of], index.astype(np.uint32), hi[who], lo[who], sets.n[who].astype(np.uint32), home[who]))
                yield pa.RecordBatch.from_arrays([pa.array(ps, pa.int32()), pa.array(blobs, pa.binary())], ["p", "blob"])
        tidy()

    return run


def _proposed(g, place, n, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Indices of pairs that share an n-gram which may be their first common one; rows come sorted by ``g``.

    With overlap o, the j-th common n-gram stands at most n - o places later in either order,
    so o + 1 - max(L) first n-grams at least are common (a set has n - L + 1 of them, L =
    ceil(percent * n / 100)), and the first of them stands that many before the end.
    """
    n, place = n.astype(np.int64), place.astype(np.int64)
    found_i, found_j = [], []
    for d in range(1, FEW):
        i = np.flatnonzero(g[d:] == g[:-d])
        if not len(i):
            break
        j = i + d
        ni, nj, need = n[i], n[j], _need(n[i], n[j], percent)
        ok = 100 * np.minimum(ni, nj) >= percent * np.maximum(ni, nj)
        ok &= np.minimum(ni - place[i], nj - place[j]) + np.minimum(place[i], place[j]) >= need
        common = np.maximum(1, need + 1 - _least(np.maximum(ni, nj), percent))
        ok &= (place[i] <= ni - _least(ni, percent) + 1 - common) & (place[j] <= nj - _least(nj, percent) + 1 - common)
        found_i.append(i[ok])
        found_j.append(j[ok])
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *found_i]), np.concatenate([none, *found_j])


MET = "gram long, sid binary, n long, held long, sid2 binary, home long"


def _met(percent: int):
    """Pairs (sid, sid2) that n-grams of few sets propose; of the others each set (sid2 null) with how many hold the n-gram."""

    def rows(gram, sid, n, held, sid2, home):
        size = len(sid)
        cols = [pa.nulls(size, pa.int64()) if c is None else pa.array(np.asarray(c).view(np.int64)) for c in (gram, n, held, home)]
        return pa.RecordBatch.from_arrays([cols[0], pa.array(sid, pa.binary()), cols[1], cols[2], pa.nulls(size, pa.binary()) if sid2 is None else pa.array(sid2, pa.binary()), cols[3]], ["gram", "sid", "n", "held", "sid2", "home"])

    def run(batches):
        parts: dict[int, list] = {}
        for batch in batches:
            for p, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                parts.setdefault(p, []).append(raw)
        while parts:
            cols = []
            for raw in parts.popitem()[1]:
                g, place, index, hi, lo, n, home = unsqueeze(raw)
                cols.append((g, place, hi[index], lo[index], n[index], home[index]))
            cols = [np.concatenate(c) for c in zip(*cols, strict=True)]
            order = np.argsort(cols[0], kind="stable")
            v = cols[0][order]
            same = np.zeros(len(v), bool)
            same[1:] = v[1:] == v[:-1]
            same[:-1] |= v[1:] == v[:-1]
            cols = [c[order[same]] for c in cols]  # of n-grams met once only, nothing is left
            order = np.lexsort((cols[3], cols[2], cols[0]))
            cols = [c[order] for c in cols]
            g, hi, lo = cols[0], cols[2], cols[3]
            new = np.ones(len(g), bool)
            new[1:] = (g[1:] != g[:-1]) | (hi[1:] != hi[:-1]) | (lo[1:] != lo[:-1])
            g, place, hi, lo, n, home = (c[new] for c in cols)
            if not len(g):
                continue
            run_no = np.cumsum(np.concatenate(([True], g[1:] != g[:-1]))) - 1
            held = np.bincount(run_no)[run_no]
            few = np.flatnonzero((held > 1) & (held <= FEW))
            i, j = _proposed(g[few], place[few], n[few], percent)
            if len(i):
                i, j = few[i], few[j]
                order = np.lexsort((lo, hi))
                who = np.zeros(len(hi), np.int64)
                who[order] = np.cumsum(np.concatenate(([True], (hi[order][1:] != hi[order][:-1]) | (lo[order][1:] != lo[order][:-1])))) - 1
                swap = (home[j] < home[i]) | ((home[j] == home[i]) & (who[j] < who[i]))  # who has the lesser home leads
                i, j = np.where(swap, j, i), np.where(swap, i, j)
                _, once = np.unique(who[i] * len(hi) + who[j], return_index=True)
                i, j = i[once], j[once]
                for at in range(0, len(i), 50_000):
                    a, b = i[at : at + 50_000], j[at : at + 50_000]
                    yield rows(None, _sid(hi[a], lo[a]), (n[a] + n[b]).astype(np.int64), None, _sid(hi[b], lo[b]), home[a])
            many = np.flatnonzero(held > FEW)
            for at in range(0, len(many), 50_000):
                a = many[at : at + 50_000]
                yield rows(g[a], _sid(hi[a], lo[a]), n[a].astype(np.int64), held[a], None, None)
        tidy()

    return run


def _with_bitmaps(k: int):
    def run(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                sets = Sets(data, offs, k)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sets.n, pa.int64()), pa.array(sets.bitmaps(), pa.binary()), part.column(1)], ["sid", "n", "bits", "text"])
        tidy()

    return run


# Tiles


def _grouped(batches, keys: int):
    """(key, rows) of each run of rows that are equal in the first ``keys`` columns, which sort the rows."""
    held, last = [], None

    def rows():
        return held[0] if len(held) == 1 else pa.Table.from_batches(held).combine_chunks().to_batches()[0]

    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(i).to_numpy() for i in range(keys)]
        new = np.zeros(batch.num_rows, bool)
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        starts = [0, *np.flatnonzero(new).tolist(), batch.num_rows]
        for a, b in zip(starts[:-1], starts[1:], strict=True):
            key = tuple(int(c[a]) for c in cols)
            if key != last and held:
                yield last, rows()
                held = []
            last = key
            held.append(batch.slice(a, b - a))
    if held:
        yield last, rows()


def _differing_bits(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Bits that differ between all rows of ``a`` and of ``b``; the longer bitmaps fold to the shorter."""
    while a.shape[1] > b.shape[1]:
        a = a[:, : a.shape[1] // 2] ^ a[:, a.shape[1] // 2 :]
    while b.shape[1] > a.shape[1]:
        b = b[:, : b.shape[1] // 2] ^ b[:, b.shape[1] // 2 :]
    out = np.zeros((len(a), len(b)), np.int32)
    for w in range(a.shape[1]):
        out += np.bitwise_count(a[:, w, None] ^ b[None, :, w])
    return out


def candidates(side: np.ndarray, n: np.ndarray, label: np.ndarray, bits: list[bytes], percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Pairs between side 0 and side 1 (within side 0 where there is no other) with different
    labels whose sizes and bitmaps allow a link."""
    width = np.array([len(x) for x in bits])
    two = bool(side.any())
    found_i, found_j = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
    classes = {}
    for s in (0, 1) if two else (0,):
        for w in np.unique(width[side == s]).tolist():
            who = np.flatnonzero((side == s) & (width == w))
            who = who[np.argsort(n[who], kind="stable")]
            classes[s, w] = who, np.frombuffer(b"".join(bits[i] for i in who), "<u8").reshape(len(who), -1)
    for (s, w), (a, x) in classes.items():
        if s:
            continue
        for (s2, w2), (b, y) in classes.items():
            if s2 != int(two) or (not two and w2 < w):
                continue
            step = max(1, (1 << 19) // max(1, len(b)))
            for at in range(0, len(a), step):
                i = a[at : at + step]
                low, high = np.searchsorted(n[b], [-(-percent * n[i[0]] // 100), 100 * n[i[-1]] // percent + 1])
                if low >= high:
                    continue
                j = b[low:high]
                ni, nj = n[i][:, None], n[j][None, :]
                most = (ni + nj - _differing_bits(x[at : at + step], y[low:high])) >> 1
                ok = (most >= _need(ni, nj, percent)) & (label[i][:, None] != label[j][None, :])
                ok &= 100 * np.minimum(ni, nj) >= percent * np.maximum(ni, nj)
                u, v = np.nonzero(ok)
                found_i.append(i[u])
                found_j.append(j[v])
    return np.concatenate(found_i), np.concatenate(found_j)


def _numbered(values: list[bytes]) -> np.ndarray:
    seen: dict[bytes, int] = {}
    return np.array([seen.setdefault(v, len(seen)) for v in values], np.int64)


def _may_link(percent: int):
    """Rows (tile, side, sid, label, n, bits), sorted by tile: the sets that are to be counted, and the tile's pairs of them."""

    def run(batches):
        for (tile,), rows in _grouped(batches, 1):
            sid = rows.column(2).to_pylist()
            who = _numbered(sid)
            n = rows.column(4).to_numpy()
            i, j = candidates(rows.column(1).to_numpy(), n, _numbered(rows.column(3).to_pylist()), rows.column(5).to_pylist(), percent)
            a, b = np.minimum(who[i], who[j]), np.maximum(who[i], who[j])
            pairs = np.unique((a * len(sid) + b)[a < b])
            if not len(pairs):
                continue
            both, at = np.unique(np.concatenate((pairs // len(sid), pairs % len(sid))), return_inverse=True)
            row_of = np.zeros(len(sid), np.int64)
            row_of[who[::-1]] = np.arange(len(sid))[::-1]  # a set's first row
            need = row_of[both]
            names = [sid[x] for x in need.tolist()]
            blob = squeeze(*at.astype(np.uint32).reshape(2, -1), n[need].astype(np.int64), np.frombuffer(b"".join(names), "<u8"))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(len(names) + 1, tile)), pa.array([-1, *range(len(names))], pa.int32()), pa.array([None, *names], pa.binary()), pa.array([blob] + [None] * len(names), pa.binary())], ["tile", "at", "sid", "pairs"]
            )
        tidy()

    return run


def _segments(k: int, order):
    """Each set of a tile as rows of its fragments of the global order."""

    def run(batches):
        for batch in batches:
            for part, data, offs in text_slices(batch):
                classes, cuts = order.value
                sets = Sets(data, offs, k, classes)
                where = np.searchsorted(cuts, place_in_order(sets.gram, classes), side="right")
                size = np.bincount(sets.row * FRAGMENTS + where, minlength=len(sets.n) * FRAGMENTS)
                ends = np.cumsum(size) * 8
                raw = sets.gram.tobytes()
                some = np.flatnonzero(size)
                segments = [raw[b - 8 * s : b] for b, s in zip(ends[some].tolist(), size[some].tolist(), strict=True)]
                row = pa.array(some // FRAGMENTS)
                yield pa.RecordBatch.from_arrays([part.column(0).take(row), pa.array(some % FRAGMENTS, pa.int32()), part.column(1).take(row), pa.array(segments, pa.binary())], ["tile", "fragment", "at", "segment"])
        tidy()

    return run


def shared_counts(gram: np.ndarray, owner: np.ndarray, sets: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """N-grams that the sets i and j share, for each pair of arrays i, j; (gram, owner) rows are distinct."""
    out = np.zeros(len(i), np.int64)
    order = np.argsort(gram, kind="stable")
    v = gram[order]
    if not len(v):
        return out
    run = np.cumsum(np.concatenate(([True], v[1:] != v[:-1]))) - 1
    several = np.bincount(run)[run] > 1
    own, run = owner[order][several], run[several]
    if not len(run):
        return out
    col = np.cumsum(np.concatenate(([True], run[1:] != run[:-1]))) - 1
    held = np.bincount(own, minlength=sets)
    total = int(col[-1]) + 1
    if sets <= 2 * SIDE and int(held[i].sum()) > sets * sets * total // 256:  # most sets against most: a product of 0/1 matrices
        step = max(256, (1 << 22) // sets)
        for at in range(0, total, step):
            a, b = np.searchsorted(col, [at, at + step])
            m = np.zeros((sets, min(step, total - at)), np.float32)
            m[own[a:b], col[a:b] - at] = 1
            out += (m @ m.T)[i, j].astype(np.int64)
        return out
    order = np.argsort(own, kind="stable")  # else each pair looks one set's n-grams up in the other's
    col, start = col[order], np.cumsum(held) - held
    known = own[order] * total + col
    bounds = np.cumsum(held[i])
    at = 0
    while at < len(i):
        end = max(at + 1, int(np.searchsorted(bounds, (bounds[at - 1] if at else 0) + (1 << 20), side="right")))
        size = held[i[at:end]]
        flat = np.repeat(start[i[at:end]] - (np.cumsum(size) - size), size) + np.arange(size.sum())
        asked = np.repeat(j[at:end] * total, size) + col[flat]
        found = np.searchsorted(known, asked)
        found[found == len(known)] = 0
        out[at:end] = np.bincount(np.repeat(np.arange(end - at), size), weights=known[found] == asked, minlength=end - at)
        at = end
    return out


def _partial(batches):
    """Rows (tile, fragment, at, segment): the tile's pairs first, then its sets; partial overlaps of the pairs."""
    for (tile, fragment), rows in _grouped(batches, 2):
        at, raw = rows.column(2).to_numpy(), rows.column(3)
        if at[0] >= 0:
            continue
        pairs = raw[0].as_py()
        i, j, n, _ = unsqueeze(pairs)
        first = np.ones(len(at), bool)
        first[1:] = at[1:] != at[:-1]
        first[0] = False
        segments = raw.filter(pa.array(first)).to_pylist()
        owner = np.repeat(at[first].astype(np.int64), [len(s) // 8 for s in segments])
        both = shared_counts(np.frombuffer(b"".join(segments), np.uint64), owner, len(n), i.astype(np.int64), j.astype(np.int64))
        yield pa.RecordBatch.from_arrays([pa.array([tile]), pa.array([fragment], pa.int32()), pa.array([squeeze(both.astype(np.uint32))], pa.binary()), pa.array([None if fragment else pairs], pa.binary())], ["tile", "fragment", "both", "pairs"])
    tidy()


def forest(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least node that each of n nodes reaches by the edges a, b."""
    low = np.arange(n)
    while True:
        m = np.minimum(low[a], low[b])
        new = low.copy()
        for end in (a, b, low[a], low[b]):
            np.minimum.at(new, end, m)
        new = new[new]
        if (new == low).all():
            return low
        low = new


def _links(percent: int):
    """Rows (tile, fragment, both, pairs): the fragments' counts summed for each pair, and a forest of the links."""

    def run(batches):
        for _, rows in _grouped(batches, 1):
            parts = dict(zip(rows.column(1).to_pylist(), rows.column(2).to_pylist(), strict=True))
            blobs = [x for x in rows.column(3).to_pylist() if x is not None]
            if not blobs:
                continue
            i, j, n, names = unsqueeze(blobs[0])
            both = np.zeros(len(i), np.int64)
            for raw in parts.values():
                both += unsqueeze(raw)[0]
            linked = 100 * both >= percent * (n[i] + n[j] - both)
            low = forest(len(n), i[linked].astype(np.int64), j[linked].astype(np.int64))
            node = np.flatnonzero(low != np.arange(len(n)))
            if len(node):
                sids = names.reshape(-1, 2)
                a, b = ([x.tobytes() for x in sids[k]] for k in (node, low[node]))
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.binary()), pa.array(b, pa.binary())], ["a", "b"])
        tidy()

    return run


def tile_links(tiles: DataFrame, texts: DataFrame, k: int, percent: int, order) -> DataFrame:
    """(a, b): a forest of the links within each tile, of tiles (tile, side, sid, label).

    ``texts`` has sid, n, bits and text of every set. Sets of one label are not compared.
    """
    rows = tiles.join(texts.select("sid", "n", "bits"), "sid").select("tile", "side", "sid", "label", "n", "bits")
    rows = rows.repartition("tile").sortWithinPartitions("tile", "side")
    left = stage(rows.mapInArrow(_may_link(percent), "tile long, at int, sid binary, pairs binary"), "tile-pairs")
    pairs, sets = left.where("at < 0"), left.where("at >= 0").select("sid", "tile", "at")
    found = texts.select("sid", "text").join(sized(sets), "sid").select("tile", "at", "text")
    segments = found.mapInArrow(_segments(k, order), "tile long, fragment int, at int, segment binary")
    every = F.explode(F.sequence(F.lit(0), F.lit(FRAGMENTS - 1))).alias("fragment")
    segments = segments.unionByName(pairs.select("tile", every, "at", F.col("pairs").alias("segment")))
    counted = segments.repartition("tile", "fragment").sortWithinPartitions("tile", "fragment", "at").mapInArrow(_partial, "tile long, fragment int, both binary, pairs binary")
    return stage(counted.repartition("tile").sortWithinPartitions("tile", "fragment").mapInArrow(_links(percent), "a binary, b binary"), "links")


def _shares(count: Column, sum_n: Column) -> Column:
    """Parts of a group so that each holds about SIDE sets and SIDE_GRAMS n-grams at most."""
    return F.ceil(F.greatest(count / F.lit(SIDE), sum_n / F.lit(SIDE_GRAMS))).cast("long")


def _pair_tiles(pairs: DataFrame) -> DataFrame:
    """(tile, side, sid, label): proposed pairs by the home of the set that leads, which near copies mostly share."""
    buckets = max(1, -(-pairs.count() // SIDE))
    dealt = pairs.withColumn("bucket", F.pmod("home", F.lit(buckets)))
    shares = dealt.groupBy("bucket").agg(_shares(F.count("*"), F.sum("n")).alias("shares"))
    dealt = dealt.join(shares, "bucket").withColumn("tile", F.xxhash64(F.lit("pairs"), "bucket", F.pmod(F.xxhash64("sid"), F.col("shares"))))
    side = F.explode(F.array(F.struct(F.lit(0).alias("side"), F.col("sid").alias("sid")), F.struct(F.lit(1).alias("side"), F.col("sid2").alias("sid")))).alias("s")
    return dealt.select("tile", side).select("tile", "s.side", "s.sid").distinct().withColumn("label", F.col("sid"))


def _anchors(large: DataFrame) -> DataFrame:
    """sid, n, anchor, score: the first n-gram of a set that most sets hold, and how common its first n-grams are."""
    top = F.max(F.struct("held", "gram"))["gram"].alias("anchor")
    return large.groupBy("sid").agg(F.first("n").alias("n"), top, F.sum("held").alias("score"))


def _leader_tiles(anchors: DataFrame, percent: int) -> DataFrame:
    """(tile, side, sid, label): the sets of each anchor, in shares, against a few that lead it.

    Of each band of sizes those lead whose first n-grams are the most common, as they differ
    least from the rest. Small anchors share tiles.
    """
    band = F.floor(F.log(F.col("n").cast("double")) / F.lit(float(-np.log(percent / 100)))).alias("band")
    nth = F.row_number().over(Window.partitionBy("anchor", "band").orderBy(F.desc("score"), "sid"))
    lead = anchors.select("sid", "anchor", "score", band).withColumn("nth", nth).where(F.col("nth") <= LEADERS).select("sid", "anchor")
    sizes = anchors.groupBy("anchor").agg(F.count("*").alias("c"), _shares(F.count("*"), F.sum("n")).alias("shares"))
    buckets = max(1, -(-anchors.count() // (SIDE // 2)))
    place = F.when((F.col("c") < SIDE // 4) & (F.col("shares") == 1), F.pmod(F.xxhash64("anchor"), F.lit(buckets)))
    tile = F.when(place.isNotNull(), F.xxhash64(F.lit("few"), place)).otherwise(F.xxhash64(F.lit("lead"), "anchor", "share")).alias("tile")
    leaders = lead.join(sizes, "anchor").withColumn("share", F.explode(F.sequence(F.lit(0).cast("long"), F.col("shares") - 1))).select(tile, F.lit(0).alias("side"), "sid")
    members = anchors.join(sizes, "anchor").withColumn("share", F.pmod(F.xxhash64("sid"), F.col("shares"))).select(tile, F.lit(1).alias("side"), "sid")
    return leaders.unionByName(members).withColumn("label", F.col("sid"))


def _block_tiles(large: DataFrame, anchors: DataFrame, labels: DataFrame) -> DataFrame:
    """(tile, side, sid, label): the sets that share an n-gram with sets of other labels, block against block.

    Blocks are parts of an anchor's sets, those of its largest component apart, as they need
    not meet each other. An n-gram whose sets are in more than BLOCKS blocks has its own.
    """
    of_set = labels.withColumnRenamed("node", "sid")
    known = large.select("gram", "sid", "n").join(of_set, "sid", "left").withColumn("label", F.coalesce("label", "sid"))
    per = known.groupBy("gram").agg(F.min("label").alias("low"), F.max("label").alias("high"), _shares(F.count("*"), F.sum("n")).alias("own"))
    mixed = known.join(per.where("low <> high").select("gram", "own"), "gram")

    marked = anchors.select("sid", "n", "anchor").join(of_set, "sid", "left").withColumn("label", F.coalesce("label", "sid"))
    major = marked.groupBy("anchor", "label").agg(F.count("*").alias("c")).groupBy("anchor").agg(F.max(F.struct("c", "label"))["label"].alias("major"))
    marked = marked.join(major, "anchor").withColumn("main", F.col("label") == F.col("major"))
    parts = marked.groupBy("anchor", "main").agg(_shares(F.count("*"), F.sum("n")).alias("shares"))
    block = F.xxhash64("anchor", "main", F.pmod(F.xxhash64("sid"), F.col("shares"))).alias("block")
    mixed = stage(mixed.join(marked.join(parts, ["anchor", "main"]).select("sid", block), "sid"), "mixed-grams")

    blocks = mixed.groupBy("gram").agg(F.count_distinct("block").alias("blocks"))
    own = F.xxhash64(F.lit("own"), "gram", F.pmod(F.xxhash64("sid"), F.col("own")))
    mixed = mixed.join(blocks, "gram").withColumn("block", F.when(F.col("blocks") > BLOCKS, own).otherwise(F.col("block")))
    mixed = mixed.select("gram", "sid", "label", "block")
    met = mixed.groupBy("gram", "block").agg(F.min("label").alias("low"), F.max("label").alias("high"))
    rows = mixed.join(met, ["gram", "block"])
    other = met.select("gram", *[F.col(c).alias(f"{c}2") for c in ("block", "low", "high")])
    both = rows.join(other, "gram").where("NOT (low = high AND low2 = high2 AND low = low2)")
    tile = F.xxhash64(F.least("block", "block2"), F.greatest("block", "block2")).alias("tile")
    return both.select(tile, (F.col("block") > F.col("block2")).cast("int").alias("side"), "sid", "label").distinct()


def _joined(labels: DataFrame | None, links: DataFrame) -> DataFrame:
    """(node, label) after joining the components that new links meet."""
    if labels is None:
        return stage(components(links), "labels")
    of_a, of_b = (labels.select(F.col("node").alias(x), F.col("label").alias(f"l{x}")) for x in ("a", "b"))
    meet = links.join(of_a, "a", "left").join(of_b, "b", "left").select(F.coalesce("la", "a").alias("u"), F.coalesce("lb", "b").alias("v"))
    joined = stage(components(meet), "joined")
    moved = labels.join(joined.select(F.col("node").alias("label"), F.col("label").alias("to")), "label", "left").select("node", F.coalesce("to", "label").alias("label"))
    fresh = joined.join(labels.select("node"), "node", "left_anti").select("node", "label")
    return stage(moved.unionByName(fresh), "labels")


def ngram_groups(docs: DataFrame, k: int = 3, percent: int = 90) -> DataFrame:
    """doc_id, n_shingles, component_id for every row of ``docs`` (doc_id, text).

    Words are runs without ASCII white space, A-Z lower-cased; a set holds the distinct runs
    of ``k`` words, or the whole sequence where a text has fewer. Documents link when
    100 * intersection >= percent * union; component_id is the smallest doc_id reachable.
    Null and blank texts have an empty set and link with nothing: their component is their
    own id. Null ids are passed over when the smallest id is taken. Rows that repeat an id
    are documents of their own under that id. An empty table gives an empty result; other
    columns are ignored.
    """
    members = ngram_rows(docs, k, percent)
    lowest = members.where("n > 0").groupBy("label").agg(F.min("doc_id").alias("low"))
    return members.join(lowest, "label", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") > 0, F.col("low")).otherwise(F.col("doc_id")).alias("component_id"))


def text_key(text: Column) -> Column:
    """Hash that tells the texts of one id apart; null counts as empty."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def ngram_rows(docs: DataFrame, k: int, percent: int) -> DataFrame:
    """doc_id, key, n, label for every row of ``docs``: the text's key, the size of its set, and its component.

    Labels are of sets, so rows under one id with texts of different components differ by them.
    """
    docs = only(docs, "doc_id", "text")
    spark = docs.sparkSession
    small_batches(spark)
    held = staged_tables()
    ids = docs.schema["doc_id"].dataType.simpleString()
    docs = docs.withColumn("key", text_key(F.col("text")))  # ids may repeat with other texts
    told = stage(docs.mapInArrow(_describe(k, SKETCH), f"doc_id {ids}, key long, n long, sid binary, sketch binary"), "sets")
    rows = told.where("sketch is null").drop("sketch")
    order = spark.sparkContext.broadcast(global_order(told.where("sketch is not null").select("sketch")))
    total = rows.agg(F.sum("n")).first()[0] or 0
    parts = max(1, -(-total * (100 - percent) // (100 * SHARE)))
    sent = docs.select("text").mapInArrow(_prefixes(k, percent, parts, order), "p int, blob binary")
    met = stage(sent.repartition(parts, "p").mapInArrow(_met(percent), MET), "met")
    pairs, large = met.where("sid2 is not null").select("sid", "sid2", "n", "home"), met.where("sid2 is null").select("gram", "sid", "n", "held")

    # Texts of the sets that share a first n-gram: one document each.
    first = rows.where("n > 0").groupBy("sid").agg(F.min(F.struct("doc_id", "key")).alias("one"))
    some = met.select(F.explode(F.array("sid", "sid2")).alias("sid")).where("sid is not null").distinct()
    wanted = stage(some.join(first, "sid").select("sid", F.col("one.doc_id").alias("of"), F.col("one.key").alias("key")), "wanted")
    # An id and text in several rows gives a text several times; tiles take a set once.
    texts = docs.join(sized(wanted), (docs.key == wanted.key) & docs.doc_id.eqNullSafe(wanted.of)).select("sid", "text")
    texts = stage(texts.mapInArrow(_with_bitmaps(k), "sid binary, n long, bits binary, text string"), "set-texts")

    anchors = stage(_anchors(large), "anchors")
    tiles = stage(_pair_tiles(pairs).unionByName(_leader_tiles(anchors, percent)), "tiles")
    labels = _joined(None, tile_links(tiles, texts, k, percent, order))
    tiles = stage(_block_tiles(large, anchors, labels), "tiles")
    labels = _joined(labels, tile_links(tiles, texts, k, percent, order))

    members = rows.join(labels.withColumnRenamed("node", "sid"), "sid", "left").withColumn("label", F.coalesce("label", "sid"))
    members = stage(members.select("doc_id", "key", "n", "label"), "members")
    drop_staged(spark, held, keep=members)
    order.destroy()
    return members
