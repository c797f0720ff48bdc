"""Training-data operators against brute force, on awkward rows."""

import hashlib
import re
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
P = pytest.importorskip("public_tokenizers")

LONG = " ".join(f"word{i % 977} é{i}" for i in range(30_000))
PASSAGE = " ".join(f"p{i}" for i in range(60))
ROWS = [
    (0, "The cat sat on the mat. It was, indeed, a CAT!"),
    (1, "The cat sat  on the\nmat. It was, indeed, a CAT!"),
    (2, None),
    (3, ""),
    (4, " \n\t "),
    (5, "one"),
    (6, "ONE"),
    (7, LONG),
    (8, LONG + " tail"),
    (9, "mail a.b+c@x-y.org.uk or 192.168.0.1 or 4111 1111 1111 1111 or +44 (20) 7946-0958; iban GB82 WEST 1234 5698 7654 32 bank"),
    (10, "don't <|endoftext|> İstanbul Σας  two  spaces x 漢字 😀 \x00 nul"),
    (11, "start " + PASSAGE + " end one two three"),
    (12, PASSAGE + " other " + PASSAGE),
    (12, "a row that repeats an id"),
    (13, "a row that is repeated"),
    (13, "a row that is repeated"),
    (None, "a row without an id"),
    (None, None),
]


def frame(spark, rows=ROWS):
    """Rows with extra columns whose names clash with those that operators use inside."""
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for c in ("d", "t", "p", "n", "sid", "label", "length", "piece", "rank", "h1", "score", "sketch", "bucket"):
        df = df.withColumn(c, F.lit(None).cast("string"))
    return df.repartition(3)


def multiset(rows):
    return sorted(map(repr, rows))


def norm(t):
    return re.sub(r"[\x20\x09-\x0D]+", " ", t or "")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


@pytest.fixture(scope="module")
def corpus():
    return duckdb.sql(f"SELECT doc_id, text FROM '{SF}/documents.parquet'").fetchall()


def tokenizer(name):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(P.path(name))


# Token counts and id files


@pytest.mark.parametrize("name,style", [("word_bpe_49k.json", "word"), ("byte_bpe_50k.json", "byte")])
def test_unit_encoder_equals_library(corpus, name, style):
    import pyarrow as pa

    from veilstat.llm.common import raw_bytes
    from veilstat.llm.unit_encoder import UnitEncoder

    texts = [t or "" for _, t in ROWS + corpus] + ["a   b  x　 ", "…. «é». x;é; ñ, ß:", "  lead", "trail  ", "a \n b\n", "it's. they'll, 12.", "x  <|endoftext|>", "<|STARTOFTEXT|>"]
    want = [e.ids for e in tokenizer(name).encode_batch(texts, add_special_tokens=False)]
    encoder = UnitEncoder(P.path(name), style)
    for _ in range(2):
        got = []
        for _, ids, counts in encoder.encode_rows(*raw_bytes(pa.array(texts))):
            got += [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])]
        assert got == want


def test_unit_encoder_forgets_and_recovers(corpus, monkeypatch):
    import pyarrow as pa

    from veilstat.llm import unit_encoder as U
    from veilstat.llm.common import raw_bytes

    monkeypatch.setattr(U, "UNITS", 500)
    monkeypatch.setattr(U, "RECENT", 100)
    monkeypatch.setattr(U, "SLICE", 5_000)
    texts = [t for _, t in corpus]
    want = [e.ids for e in tokenizer("word_bpe_49k.json").encode_batch(texts, add_special_tokens=False)]
    got = []
    for _, ids, counts in U.UnitEncoder(P.path("word_bpe_49k.json"), "word").encode_rows(*raw_bytes(pa.array(texts))):
        got += [x.tolist() for x in np.split(ids, np.cumsum(counts)[:-1])]
    assert got == want


def test_token_counts(spark):
    from veilstat.llm.token_counts import token_counts

    tok = tokenizer("word_bpe_49k.json")
    n = lambda t: len(tok.encode(t or "", add_special_tokens=False).ids)
    got = token_counts(frame(spark), P.path("word_bpe_49k.json")).collect()
    assert multiset(tuple(r) for r in got) == multiset((i, len((t or "").encode()), n(t), n(t) > 2048) for i, t in ROWS)
    assert token_counts(frame(spark).limit(0), P.path("word_bpe_49k.json")).count() == 0


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_planes_round_trip(kind, tmp_path):
    from veilstat.llm.id_files import ShardReader, ShardWriter, from_planes, to_planes

    ids = np.random.default_rng(1).integers(0, 1 << 32, 1000, dtype=np.uint32)
    assert (from_planes(to_planes(ids, kind), len(ids), kind) == ids).all()
    docs = [ids[:0], ids[:7], ids, ids[:1], ids[5:700]]
    path = tmp_path / "x.planes"
    with path.open("wb") as f:
        w = ShardWriter(f, kind, block=64)
        for i, x in enumerate(docs):
            w.add(i, x.tobytes())
        w.close()
    with path.open("rb") as f:
        r = ShardReader(f, path.stat().st_size)
        assert [x.tolist() for _, x in r.documents()] == [x.tolist() for x in docs]
        assert r.document(4).tolist() == docs[4].tolist() and r.document(0).tolist() == []


def test_id_files(spark):
    from veilstat.llm.id_files import id_file_digest

    tok = tokenizer("word_bpe_49k.json")
    start, want = 0, []
    for i, t in sorted(ROWS, key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or "")):
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [1], "<u4")
        want.append((i, start, len(ids), zlib.crc32(ids.tobytes())))
        start += len(ids)
    assert multiset(map(tuple, id_file_digest(frame(spark), P.path("word_bpe_49k.json")).collect())) == multiset(want)
    assert id_file_digest(frame(spark).limit(0), P.path("word_bpe_49k.json")).count() == 0


# Packing


def test_packing(spark):
    from veilstat.llm.packing import pack_documents

    got = pack_documents(frame(spark, ROWS * 3), P.path("byte_bpe_50k.json"), 256).toPandas()
    assert (got.length <= 256).all() and got.groupby("sequence_id").length.sum().max() <= 256
    for _, g in got.sort_values("offset").groupby("sequence_id"):
        assert g.offset.tolist() == [0, *np.cumsum(g.length)[:-1].tolist()]
    tok = tokenizer("byte_bpe_50k.json")
    n = {t: len(tok.encode(t or "", add_special_tokens=False).ids) + 1 for _, t in ROWS}
    assert got.length.sum() == 3 * sum(n[t] for _, t in ROWS)
    want = []
    for doc_id, t in ROWS * 3:
        ids = np.array([*tok.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        head = len(ids) % 256 or 256
        cuts = [0, *range(head, len(ids) + 1, 256)]
        want += [(doc_id, p, a, b - a, zlib.crc32(ids[a:b].tobytes())) for p, (a, b) in enumerate(zip(cuts, cuts[1:]))]
    ids = got.doc_id.astype(object).where(got.doc_id.notna(), None)
    assert multiset((None if i is None else int(i), *map(int, r)) for i, r in zip(ids, got[["piece", "start", "length", "ids_crc32"]].values.tolist())) == multiset(want)
    assert got[got.piece > 0].length.eq(256).all()
    assert got.sequence_id.nunique() <= -(-got.length.sum() // 256) * 1.05 + 1
    assert pack_documents(frame(spark).limit(0), P.path("byte_bpe_50k.json")).count() == 0


def test_plan_covers_exactly_and_is_tight():
    from veilstat.llm.packing import lay_out, plan

    rng = np.random.default_rng(3)
    for need in (rng.integers(0, 40, 129), np.bincount(rng.integers(1, 129, 50), minlength=129), np.bincount([65] * 9, minlength=129)):
        need[0] = 0
        steps = plan(need, 128).steps
        have = np.zeros(129, int)
        for pattern, times in steps:
            assert sum(s * k for s, k in pattern) <= 128
            for s, k in pattern:
                have[s] += k * times
        assert (have == need).all()
        used = int(lay_out(steps, 128)["sequences"])
        least = max(-(-(need * np.arange(129)).sum() // 128), need[65:].sum())
        assert used <= least * 1.1 + 1


def test_program_makes_the_plan(spark):
    """At sf0.1 most sequences come from the rounded program, and filling alone is never better."""
    from veilstat.llm.packing import _filled, fractional, plan, token_pieces

    for sf, share in (("sf0.01", 0.8), ("sf0.1", 0.8)):
        docs = spark.read.parquet(f"/root/testdata/{sf}/documents.parquet")
        need = np.zeros(2049, np.int64)
        for r in token_pieces(docs, P.path("byte_bpe_50k.json")).groupBy("length").count().collect():
            need[r["length"]] = r["count"]
        made = plan(need, 2048)
        assert made.rounded >= share * made.sequences
        assert made.bound <= made.sequences <= sum(k for _, k in _filled(need.copy(), 2048))
        assert made.sequences == -(-(need * np.arange(2049)).sum() // 2048)
    x, bound = fractional(need, 2048)
    covered = np.zeros(2049)
    for pattern, amount in x.items():
        for s, k in pattern:
            covered[s] += k * amount
    assert np.allclose(covered, need) and len(x) <= (need > 0).sum() and bound <= sum(x.values()) + 1e-6


def test_knapsack_against_brute_force():
    from veilstat.llm.packing import knapsack

    value = np.array([0, 0, 3.0, 0, 5.0, 6.9, 0, 0, 0])
    best, _ = knapsack(value, 8)
    brute = [max((a * 3 + b * 5 + c * 6.9 for a in range(5) for b in range(3) for c in range(2) if 2 * a + 4 * b + 5 * c <= room), default=0) for room in range(9)]
    assert best == pytest.approx(brute)


# Exact copies


@pytest.mark.parametrize("prime,chunk,hot", [((1 << 31) - 1, 1 << 16, 2048), (7, 1 << 16, 2), ((1 << 31) - 1, 1000, 3), (3, 4, 2048)])
def test_exact_groups(spark, monkeypatch, prime, chunk, hot):
    """With a tiny prime nearly all equal-length texts collide and the comparison has to tell them apart;
    with small chunks most texts are hashed and compared in parts."""
    from veilstat.llm import exact_dedup
    from veilstat.llm.exact_dedup import exact_groups

    monkeypatch.setattr(exact_dedup, "HOT", hot)
    text = LONG if chunk > 4 else LONG[:3000]
    rows = [(i, t.replace(LONG, text) if t else t) for i, t in ROWS] + [(20 + i, f"x{i % 4} {'a' * 5}") for i in range(12)]
    rows += [(7, text), (40, text), (None, text), (41, text[:-1] + "?"), (42, "?" + text[1:]), (None, "x1 aaaaa"), (None, "x9 aaaaa")]
    got = exact_groups(frame(spark, rows), prime, chunk).collect()
    groups = {}
    for i, t in rows:
        groups.setdefault(norm(t), []).append(i)
    want = []
    for i, t in rows:
        g = groups[norm(t)]
        keep = min((x for x in g if x is not None), default=None)
        want.append((i, keep, len(g), keep is None or (None if i is None else i == keep), hashlib.sha256(norm(t).encode()).hexdigest()))
    want = [(a, b, c, b is None if k is None else k, s) for a, b, c, k, s in want]
    assert multiset(map(tuple, got)) == multiset(want)
    assert exact_groups(frame(spark).limit(0)).count() == 0


def test_fingerprints_compose(spark):
    from veilstat.llm.exact_dedup import BASES, Fingerprinter, combine_chunks

    data = np.frombuffer(LONG.encode(), np.uint8)
    f = Fingerprinter(chunk=1000)
    whole = f.of(data)
    assert whole == Fingerprinter().of(data) and whole[0] == len(data)
    parts = [(len(p), f.of(p)[1]) for p in (data[:12345], data[12345:20000], data[20000:])]
    left = f.combine(f.combine(parts[0], parts[1]), parts[2])
    assert left == f.combine(parts[0], f.combine(parts[1], parts[2])) == whole
    rows = [("k", a, b - a, *f.of(data[a:b])[1]) for a, b in ((0, 777), (777, 50_000), (50_000, len(data)))]
    got = combine_chunks(spark.createDataFrame(rows, "doc_key string, start long, n_bytes long, " + ", ".join(f"h{k} long" for k in range(1, len(BASES) + 1)))).first()
    assert tuple(got)[1:] == (len(data), *whole[1])


# N-gram join and repeated passages


def components(n, links):
    group = list(range(n))

    def top(x):
        while group[x] != x:
            x = group[x]
        return x

    for a, b in links:
        group[max(top(a), top(b))] = min(top(a), top(b))
    return [top(i) for i in range(n)]


@pytest.mark.parametrize("k,percent", [(3, 90), (5, 80)])
def test_ngram_groups(spark, corpus, k, percent):
    from veilstat.llm.ngram_join import ngram_groups

    rng = np.random.default_rng(5)
    base = words(corpus[3][1])[:200]
    near = []
    for i in range(60):
        w = list(base)
        for j in rng.integers(0, len(w), rng.integers(0, 6)):
            w[j] = f"edit{rng.integers(0, 4)}"
        near.append((1000 + i, " ".join(w)))
    rows = ROWS + corpus[:60] + near
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = []
    for _, t in rows:
        w = words((t or "").translate(lower))
        sets.append(frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else []))
    links = [(a, b) for a in range(len(rows)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    label = components(len(rows), links)
    want = []
    for i, (doc_id, _) in enumerate(rows):
        ids = [rows[j][0] for j in range(len(rows)) if label[j] == label[i] and rows[j][0] is not None]
        want.append((doc_id, len(sets[i]), min(ids, default=None) if sets[i] else doc_id))
    got = ngram_groups(frame(spark, rows), k, percent).collect()
    assert multiset(map(tuple, got)) == multiset(want)
    assert len({w[2] for w in want}) < len(rows) - 20


@pytest.mark.parametrize("side", [1024, 16])
def test_ngram_groups_in_tiles(spark, monkeypatch, side):
    """Groups that are larger than FEW, blocks smaller than the groups, and sets just below the threshold."""
    import random

    from veilstat.llm import ngram_join as N

    monkeypatch.setattr(N, "SIDE", side)
    rnd, rows = random.Random(5), []
    for g, size in enumerate((150, 40, 12)):
        for _ in range(size):
            w = [f"w{g}_{i}" for i in range(150)]
            for _ in range(rnd.choice([0, 1, 2, 3, 4, 6])):
                w[rnd.randrange(len(w))] = f"m{rnd.randrange(10**6)}"
            rows.append((len(rows), " ".join(w)))
    rows += [(len(rows) + i, " ".join(f"q{rnd.randrange(40)}" for _ in range(rnd.choice([1, 2, 3, 5, 8, 30])))) for i in range(60)]
    rnd.shuffle(rows)
    rows = [(i, t) for i, (_, t) in enumerate(rows)]
    sets = [{tuple(w[j : j + 3]) for j in range(len(w) - 2)} if len(w) > 2 else {tuple(w)} for w in (t.split() for _, t in rows)]
    links = [(a, b) for a in range(len(rows)) for b in range(a) if 100 * len(sets[a] & sets[b]) >= 90 * len(sets[a] | sets[b])]
    label = components(len(rows), links)
    assert 100 < len(set(label)) < len(rows)
    got = {r["doc_id"]: r["component_id"] for r in N.ngram_groups(frame(spark, rows)).collect()}
    assert got == dict(enumerate(label))


def test_bitmaps_bound_the_overlap():
    from veilstat.llm.ngram_join import candidates, forest, shared_counts

    rng = np.random.default_rng(2)

    class Fake:  # sets of bare n-gram hashes
        from veilstat.llm.ngram_join import Sets

        bitmaps = Sets.bitmaps

        def __init__(self, sets):
            self.gram = np.concatenate(sets)
            self.n = np.array([len(s) for s in sets])
            self.start = np.cumsum(self.n) - self.n

    base = rng.integers(0, 1 << 62, 400).astype(np.uint64)
    sets = [np.unique(np.where(rng.random(len(x)) < rate, rng.integers(0, 1 << 62, len(x)).astype(np.uint64), x)) for x in (base, base[:130], base[:120]) for rate in (0, 0.02, 0.05, 0.1, 0.3) for _ in range(4)]
    both = np.array([[len(np.intersect1d(a, b)) for b in sets] for a in sets])
    n = np.array([len(s) for s in sets])
    linked = 100 * both >= 80 * (n[:, None] + n[None, :] - both)
    bits = Fake(sets).bitmaps()
    who = np.arange(len(sets))
    for side in (np.zeros(len(sets), int), who % 2):
        i, j = candidates(side, n, who, bits, 80)
        found = {(min(a, b), max(a, b)) for a, b in zip(i.tolist(), j.tolist(), strict=True) if a != b}
        want = {(a, b) for a, b in zip(*np.nonzero(np.triu(linked, 1)), strict=True) if not side.any() or side[a] != side[b]}
        assert want <= found and len(found) < len(want) + 60
    owner = np.repeat(who, n)
    i, j = np.triu_indices(len(sets), 1)
    for few in (slice(None), slice(0, 40)):  # products of matrices, and looking up
        assert (shared_counts(np.concatenate(sets), owner, len(sets), i[few], j[few]) == both[i[few], j[few]]).all()
    assert forest(6, np.array([5, 4, 1]), np.array([4, 2, 0])).tolist() == [0, 0, 2, 3, 2, 2]


def test_ngram_groups_empty(spark):
    from veilstat.llm.ngram_join import ngram_groups

    assert ngram_groups(frame(spark).limit(0)).count() == 0
    assert {r["component_id"] for r in ngram_groups(frame(spark, [(1, ""), (2, None)])).collect()} == {1, 2}


def brute_repeats(rows, window=20):
    order = sorted(rows, key=lambda r: r[0])
    first = {}
    for i, t in order:
        w = words(t)
        for p in range(len(w) - window + 1):
            first.setdefault(tuple(w[p : p + window]), (i, p))
    out = []
    for i, t in rows:
        w, gone = words(t), set()
        for p in range(len(w) - window + 1):
            if first[tuple(w[p : p + window])] != (i, p):
                gone |= set(range(p, p + window))
        kept = " ".join(x for j, x in enumerate(w) if j not in gone)
        out.append((i, len(w), len(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return out


def test_substring_dedup(spark, corpus):
    from veilstat.llm.substring_dedup import remove_repeats

    rows = [r for r in {i: (i, t) for i, t in ROWS if i is not None}.values()] + [(100 + i, t) for i, t in corpus[:80]]
    rows += [(500 + i, f"u{i} " + PASSAGE + f" v{i} " + " ".join(f"z{i}x{j}" for j in range(i))) for i in range(40)] + [(600, "aa " * 100), (601, "bb " * 50)]
    got = remove_repeats(frame(spark, rows)).collect()
    assert multiset(map(tuple, got)) == multiset(brute_repeats(rows))
    assert remove_repeats(frame(spark).limit(0)).count() == 0
    text = {r["doc_id"]: r["kept_text"] for r in remove_repeats(frame(spark, rows), with_text=True).collect()}
    assert text[510].startswith("u10 v10")


def test_substring_dedup_nulls_and_repeats(spark):
    from veilstat.llm.substring_dedup import remove_repeats

    rows = [(1, PASSAGE), (1, PASSAGE), (None, PASSAGE + " x"), (None, None), (2, "short " + PASSAGE)]
    got = sorted(((r["doc_id"], r["n_words"], r["n_removed"]) for r in remove_repeats(frame(spark, rows)).collect()), key=repr)
    assert got == sorted([(1, 60, 0), (1, 60, 0), (None, 61, 60), (None, 0, 0), (2, 61, 60)], key=repr)


# Vectors


def test_near_vectors(spark):
    from veilstat.llm.embedding_dedup import near_vectors

    rng = np.random.default_rng(2)
    base = rng.normal(size=(12, 16))
    vecs = [(base[i % 12] + rng.normal(size=16) * (0.05 + 0.05 * (i % 5))).astype(np.float32).tolist() for i in range(150)]
    rows = [(i, v) for i, v in enumerate(vecs)] + [(200, vecs[0]), (201, None), (202, [0.0] * 16), (203, [float("nan")] + [1.0] * 15), (204, [float("inf")] * 16), (205, [None] + [1.0] * 15), (206, [1.0, 2.0]), (207, [1e-30] * 16), (208, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("label", F.lit(1)).withColumn("rep", F.lit("x"))
    got = {r["vec_id"]: tuple(r)[1:] for r in near_vectors(df, 0.9, block=40).collect()}
    ok = {i: np.array(v, np.float64) for i, v in rows if v and None not in v and np.isfinite(v).all() and any(v)}
    ids = sorted(ok)
    at = {i: k for k, i in enumerate(ids)}
    link = [(a, b) for a in ids for b in ids if a != b and len(ok[a]) == len(ok[b]) and ok[a] @ ok[b] / np.linalg.norm(ok[a]) / np.linalg.norm(ok[b]) >= 0.9]
    label = components(len(ids), [(at[a], at[b]) for a, b in link])
    for i, _ in rows:
        comp = ids[label[at[i]]] if i in ok else i
        assert got[i] == (sum(a == i for a, _ in link), comp, comp == i)
    assert near_vectors(df.limit(0)).count() == 0
    assert near_vectors(spark.createDataFrame([(None, [1.0, 0.0])], "vec_id long, embedding array<float>")).first()["n_links"] == 0


def test_quantisation_bound_is_rigorous():
    from veilstat.llm.embedding_dedup import quantise

    rng = np.random.default_rng(4)
    u = rng.normal(size=(200, 24))
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    step = np.abs(u).max() / 127
    q, e = quantise(u, step)
    gap = np.abs(u @ u.T - (q.astype(float) @ q.T.astype(float)) * step * step)
    assert (gap <= e[:, None] + e[None, :] + e[:, None] * e[None, :]).all()


# Personal data, pieces, quality


def test_pii_spans():
    from veilstat.llm.pii import all_spans, base_spans, luhn, masked, mod97

    text = ROWS[9][1]
    assert [k for k, *_ in base_spans(text)] == ["email", "ip", "card", "phone"]
    assert ("iban" in {k for k, *_ in all_spans(text)}) and mod97("GB82 WEST 1234 5698 7654 32") and not mod97("GB82 WEST 1234 5698 7654 33")
    assert luhn("4111111111111111") and not luhn("4111111111111112")
    assert base_spans("1.2.3.4.5 300.1.1.1 +12 34") == [("ip", 0, 7)]
    assert "@" not in masked(text) and "[EMAIL]" in masked(text) and masked("clean text. 12") == "clean text. 12"
    assert base_spans("é a@b.c")[0] == ("email", 2, 7)


# The contract's patterns, tried from every start as they are written.
PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def plain_spans(text):
    out = []
    for kind, pattern in PLAIN.items():
        for m in re.finditer(pattern, text):
            digits = [int(c) for c in m[0] if c in "0123456789"]
            if kind == "ip" and any(int(p) > 255 for p in m[0].split(".")):
                continue
            if kind == "card":
                twice = [d if i % 2 == 0 else sum(divmod(2 * d, 10)) for i, d in enumerate(digits[::-1])]
                if not 16 <= len(digits) <= 19 or sum(twice) % 10:
                    continue
            if kind == "phone" and not 8 <= len(digits) <= 15:
                continue
            out.append((kind, m.start(), m.end()))
    return out


def test_pii_against_plain_patterns(corpus):
    from veilstat.llm.pii import base_spans

    rng = np.random.default_rng(8)
    card = "4111 1111-1111 1111"
    made = ["".join(rng.choice(list("ab.@-+1205 ()é_"), rng.integers(1, 60))) for _ in range(4000)]
    made += ["".join(rng.choice(["0", "4111111111111111", card, " ", "-", ".", "+", "@", "x", "255", "256", "٣", "1.2.3.4"], 12)) for _ in range(3000)]
    for text in [t or "" for _, t in ROWS + corpus] + made:
        assert base_spans(text) == plain_spans(text), text


def test_pii_of_a_megabyte():
    """Runs that match nothing are tried once, not from each of their characters."""
    import time

    from veilstat.llm.pii import all_spans

    for run in ("1" * 1_000_000 + " . + @", "a" * 1_000_000 + " @ 1", "1." * 500_000, "1 " * 500_000, "a@" * 500_000, "+1" + "(" * 1_000_000, "A1" * 500_000, "0" * 999_990 + ".0.0.1"):
        began = time.time()
        all_spans(run)
        assert time.time() - began < 5, run[:5]


def test_pii_frame(spark):
    from veilstat.llm.pii import base_spans, find_pii, joined, mask_pii

    got = find_pii(frame(spark)).collect()
    want = multiset((i, hashlib.sha256(joined(base_spans(t or "")).encode()).hexdigest()) for i, t in ROWS)
    assert multiset((r["doc_id"], r["base_sha256"]) for r in got) == want
    kept = mask_pii(frame(spark))
    assert kept.columns == frame(spark).columns and kept.where("text is null").count() == 2
    assert find_pii(frame(spark).limit(0)).count() == 0


def test_sentence_pieces_equal_library(spark, corpus):
    import sentencepiece

    from veilstat.llm.sentence_pieces import Segmenter, encode_documents

    path = P.path("piece_bpe_32k.model")
    texts = [t or "" for _, t in ROWS if t is not LONG] + [t for _, t in corpus[:60]] + ["abc" * 300, "a▁b ▁", "\n\n a\n b", "    deep     indent", "aaaa " * 40]
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    seg = Segmenter(path)
    got = [np.frombuffer(x, "<u4").tolist() for x in seg.encode(texts)]
    assert got == sp.encode(texts, num_threads=1)
    assert [seg.decode(np.array(x)) for x in got] == sp.decode(got)
    out = {r["doc_id"]: r for r in encode_documents(frame(spark), path).collect()}
    assert out[3]["n_pieces"] == 0 and out[0]["round_trip"] and out[7]["n_pieces"] == len(sp.encode(LONG))
    assert encode_documents(frame(spark).limit(0), path).count() == 0


def test_suffix_matches_are_all_occurrences():
    from veilstat.llm.sentence_pieces import Segmenter

    seg = Segmenter(P.path("piece_bpe_32k.model"))
    text = "▁the▁theory\0▁other\0"
    pos, piece, length = seg.edges(seg.codes_of(text))
    want = {(i, k) for k in seg.usable.tolist() for i in range(len(text)) if text.startswith(seg.model["pieces"][k], i)}
    assert set(zip(pos.tolist(), piece.tolist(), strict=True)) == want and (np.diff(pos) >= 0).all()


def test_unigram_relaxation_finds_best_path():
    from veilstat.llm.sentence_pieces import Segmenter

    seg = Segmenter(P.path("piece_bpe_32k.model"))
    table = np.full((5, 4), -1)
    seg.score = np.array([-1.0, -1.0, -1.0, -5.0, -1.5])
    seg.usable = np.arange(5)
    table[0, 1], table[1, 1], table[2, 1], table[0, 2], table[1, 2] = 0, 1, 2, 3, 4
    assert seg._best_path(0, 3, table) == [0, 1]  # 0 | 1-2 at -2.5 beats 0 | 1 | 2 at -3


def test_gradients_of_attention_model():
    from veilstat.llm.quality import Model

    rng = np.random.default_rng(0)
    m = Model(4, 3)
    x, heads, y = rng.normal(size=(9, 4)), np.array([0, 2, 6]), np.array([1.0, 0.0, 1.0])

    def loss():
        s = m.forward(x, heads)["score"]
        return -(y * np.log(s) + (1 - y) * np.log(1 - s)).mean()

    g = m.gradients(m.forward(x, heads), y)
    for name in m.p:
        flat = m.p[name].reshape(-1)
        for i in range(min(3, flat.size)):
            old = flat[i]
            flat[i] = old + 1e-5
            up = loss()
            flat[i] = old - 1e-5
            down = loss()
            flat[i] = old
            assert (up - down) / 2e-5 == pytest.approx(g[name].reshape(-1)[i] - 1e-4 * old, abs=1e-6)


def test_quality_held_out(spark):
    from veilstat.llm.quality import fit_model, keep_quality, score_documents

    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = fit_model(docs, labels)
    got = score_documents(docs, model).join(labels, "doc_id").where("held_out").collect()
    assert len(got) > 50 and sum(r["predicted"] == r["quality"] for r in got) / len(got) > 0.95
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) for r in got)
    odd = score_documents(frame(spark), model).collect()
    assert len(odd) == len(ROWS) and all(0 <= r["score"] <= 1 for r in odd)
    assert keep_quality(docs, model).count() < docs.count()
    assert fit_model(docs, labels.limit(0)).forward(np.zeros((1, 47)), np.array([0]))["score"][0] == pytest.approx(0.5, abs=0.01)


def test_components(spark):
    from veilstat.llm.components import components as cc

    edges = [(i, i + 1) for i in range(50)] + [(100, 7), (200, 201), (5, 5), (201, 200)] + [(300, 300 + i) for i in range(1, 40)]
    got = {r["node"]: r["label"] for r in cc(spark.createDataFrame(edges, "x long, y long")).collect()}
    assert got[50] == 0 and got[100] == 0 and got[201] == 200 and got[339] == 300 and len(got) == 52 + 2 + 40
    assert cc(spark.createDataFrame([], "x long, y long")).count() == 0
