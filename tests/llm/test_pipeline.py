"""Every pipeline stage against brute force on what its predecessor kept."""

import re

import pytest

import corpus_pipeline as C

SF = "/root/testdata/sf0.001"
P = pytest.importorskip("public_tokenizers")


def test_stages(spark):
    from tokenizers import Tokenizer

    from veilstat.llm.pii import masked
    from veilstat.llm.quality import fit_model, score_documents

    assert [n for n, _ in C.STAGES] == ["quality", "exact_dedup", "near_dedup", "pii", "packing"]
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = [docs]
    for _, stage in C.STAGES:
        kept.append(stage(spark, kept[-1], SF).cache())
    for d in kept[1:-1]:
        assert d.columns == docs.columns and d.dtypes == docs.dtypes
    rows = [{r["doc_id"]: r for r in d.collect()} for d in kept[:-1]]

    model = fit_model(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    good = {r["doc_id"] for r in score_documents(docs, model).where("predicted = 1").collect()}
    assert set(rows[1]) == good

    norm = {}
    for i in sorted(rows[1]):
        norm.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", rows[1][i]["text"]), i)
    assert set(rows[2]) == set(norm.values())

    sets = {}
    for i, r in rows[2].items():
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), r["text"]))
        sets[i] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    ids = sorted(sets)
    low = {i: i for i in ids}

    def top(i):
        while low[i] != i:
            i = low[i]
        return i

    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                low[max(top(a), top(b))] = min(top(a), top(b))
    assert set(rows[3]) == {i for i in ids if top(i) == i}

    assert {i: r["text"] for i, r in rows[4].items()} == {i: masked(r["text"]) for i, r in rows[3].items()}
    assert all(r["n_chars"] == len(r["text"]) for r in rows[4].values())

    tok = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    got = {}
    for r in kept[-1].collect():
        got[r["doc_id"]] = got.get(r["doc_id"], 0) + r["length"]
    assert got == {i: len(tok.encode(r["text"], add_special_tokens=False).ids) + 1 for i, r in rows[4].items()}


def test_run_equals_stages(spark):
    a = C.run(spark, SF).select("doc_id", "piece", "length", "ids_crc32").collect()
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    for _, stage in C.STAGES:
        docs = stage(spark, docs, SF).cache()
    b = docs.select("doc_id", "piece", "length", "ids_crc32").collect()
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))


def test_stages_decide_by_row(spark):
    """Null, repeated and clashing ids: one row of each group stays, and no row goes for another's text."""
    far = " ".join(f"other{i}" for i in range(60))
    near = [f"word{i}" for i in range(60)]
    a, a2, a3 = (" ".join([*near[:59], x]) for x in ("x", "y", "z"))
    shape = "doc_id long, text string, lang string"

    def kept(stage, rows):
        got = stage(spark, spark.createDataFrame(rows, shape), SF)
        assert got.columns == ["doc_id", "text", "lang"]
        return sorted(map(tuple, got.collect()), key=str)

    def same(got, want):
        assert got == sorted(want, key=str)

    same(kept(C.exact_stage, [(1, "b", "fr"), (1, "b", "en"), (2, "a", "en"), (2, "b", "en"), (None, "b", "en"), (None, "c d", "en"), (None, "c  d", "en"), (5, None, "en"), (6, "", "en")]), [(1, "b", "en"), (2, "a", "en"), (None, "c  d", "en"), (5, None, "en")])

    b, b2 = a.replace("word", "term"), a2.replace("word", "term")
    rows = [(1, a, "en"), (1, a2, "en"), (1, a2, "fr"), (9, a3, "en"), (None, a2, "en"), (9, far, "en"), (None, b, "en"), (None, b2, "en"), (None, b2, "fr"), (8, None, "en"), (None, "", "en")]
    got = kept(C.near_stage, rows)
    assert set(got) <= set(rows) and len(got) == 5
    assert [r[0] for r in got if r[1] in (a, a2, a3)] == [1] and [r[0] for r in got if r[1] in (b, b2)] == [None]
    assert {(9, far, "en"), (8, None, "en"), (None, "", "en")} < set(got)


def test_stages_pass_empty_tables_and_clashing_columns(spark):
    from pyspark.sql import functions as F

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    empty, few = docs.limit(0), docs.orderBy("doc_id").limit(12).cache()
    names = ("label", "key", "sid", "n", "start", "chunk", "_id", "_mark", "_told", "row", "stays", "copies", "length", "piece", "rank", "bucket")
    wide = few
    for c in names:
        wide = wide.withColumn(c, F.lit("x"))
    for name, stage in C.STAGES:
        assert stage(spark, empty, SF).count() == 0, name
        if name == "packing":
            a, b = (stage(spark, x, SF).select("doc_id", "piece", "length", "ids_crc32").collect() for x in (few, wide))
        else:
            got = stage(spark, wide, SF)
            assert got.columns == wide.columns, name
            a, b = (x.select(*docs.columns).collect() for x in (stage(spark, few, SF), got))
        assert sorted(map(str, a)) == sorted(map(str, b)), name
