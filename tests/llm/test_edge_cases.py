"""Nulls, empty and long texts, ties, repeated rows, empty tables, clashing columns: defined results, no crash."""

import hashlib
import zlib

import numpy as np
import pytest

from subgraph_engine.llm import bpe, exact_dedup, html_text, license_scan, minhash, mixing, planes, sharding, topk, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long, size long, `_rank` int, kept string, node int, mix_id int, near_gone int, dedup_gone int"


def docs_of(spark, rows):
    full = [(i, t, "en", s, None if t is None else len(t), 7, 1, "x", 3, 4, 5, 6) for i, t, s in rows]
    return spark.createDataFrame(full, DOCS)


ODD = [
    (1, None, "b"),
    (2, "", None),
    (3, "one two three four five six", "b"),
    (4, "one  two three\tfour five six", "b"),
    (5, "word " * 30_000, "a"),
    (6, "One two three four five six", "b"),
    (7, "\x1c\x0b é漢字 🙂 <|endoftext|>", None),
    (7, "\x1c\x0b é漢字 🙂 <|endoftext|>", None),
    (None, "no id", "a"),
    (None, None, None),
    (8, "a" * 70_000, "c"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return docs_of(spark, ODD).cache()


@pytest.fixture(scope="module")
def none(spark):
    return docs_of(spark, [])


def test_exact_dedup(spark, odd, none):
    for digest in (True, False):
        rows = exact_dedup.find_duplicates(spark, odd, digest).collect()
        assert len(rows) == len(ODD)
        got = {r.doc_id: (r.keep_id, r.group_size, r.kept) for r in rows if r.doc_id not in (None, 7)}
        assert got[1] == (1, 3, True) and got[2] == (1, 3, False)
        assert got[3] == (3, 2, True) and got[4] == (3, 2, False) and got[6] == (6, 1, True)
        assert sorted(r.kept for r in rows if r.doc_id == 7) == [False, True]
        assert exact_dedup.find_duplicates(spark, none, digest).count() == 0
    kept = exact_dedup.drop_duplicates(spark, odd)
    assert kept.columns == odd.columns
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["1", "3", "5", "6", "7", "8", "None"]
    assert exact_dedup.drop_duplicates(spark, none).count() == 0


def test_sharding(spark, odd, none):
    rows = sharding.shard_rows(spark, odd, 4).collect()
    assert len(rows) == len(ODD)
    for shard in range(4):
        slots = sorted(r.slot for r in rows if r.shard == shard)
        assert slots == list(range(len(slots))) and len(slots) in (2, 3)
    for r in rows:
        text = next((t for i, t, _ in ODD if i == r.doc_id and (i is not None or (t or "") == ("no id" if r.size == 6 else ""))), None)
        assert r.size == len((text or "").encode()) + 1
        assert r.text_crc32 == zlib.crc32((text or "").encode())
    assert sharding.shard_rows(spark, none, 4).count() == 0
    assert sharding.shard_rows(spark, odd, 40).count() == len(ODD)


def test_mixing(spark, odd, none):
    rows = mixing.mix(spark, odd).collect()
    assert len(rows) == len(ODD)
    assert all(0 <= r.taken <= 2 * r.size for r in rows)
    assert mixing.mix(spark, none).count() == 0
    assert mixing.emit(spark, odd).columns == odd.columns
    assert mixing.emit(spark, none).count() == 0
    blank = docs_of(spark, [(1, "", "a"), (2, None, "b")])
    assert {r.target for r in mixing.mix(spark, blank).collect()} == {0.0}


def test_minhash(spark, odd, none):
    rows = minhash.near_duplicates(spark, odd, 4).collect()
    assert len(rows) == len(ODD)
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in rows if r.doc_id}
    assert got[1] == (0, 1, True) and got[2] == (0, 2, True)
    assert got[3] == (3, 3, True) and got[4] == (3, 3, False) and got[6] == (3, 3, False)
    assert got[5][0] == 1 and got[7][1] == 7 and got[8] == (1, 8, True)
    assert minhash.near_duplicates(spark, none).count() == 0
    kept = minhash.drop_near_duplicates(spark, odd, 4)
    assert kept.columns == odd.columns
    # texts without words stay, of each group one row stays, ids before null
    assert sorted(str(r.doc_id) for r in kept.collect()) == ["1", "2", "3", "5", "7", "8", "None", "None"]
    twins = docs_of(spark, [(None, "a b c d e f", "x"), (None, "a b c d e f", "x"), (9, "u v w x y z", "x"), (9, "other words than those are here", "x")])
    assert sorted((str(r.doc_id), r.text[:1]) for r in minhash.drop_near_duplicates(spark, twins, 4).collect()) == [("9", "o"), ("9", "u"), ("None", "a")]


def test_bpe(spark, odd, none):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(bpe.byte_bpe_path())
    rows = bpe.token_digests(odd, bpe.byte_bpe_path()).collect()
    assert len(rows) == len(ODD)
    want = sorted(
        (str(i), len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())
        for i, t, _ in ODD
        for ids in [library.encode(t or "", add_special_tokens=False).ids]
    )
    assert sorted((str(r.doc_id), r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in rows) == want
    assert bpe.token_digests(none, bpe.byte_bpe_path()).count() == 0
    clashing = odd.withColumn("token_ids", odd["size"]).withColumn("Decoded", odd["lang"])
    encoded = bpe.encode(clashing, bpe.byte_bpe_path())
    assert encoded.columns == [*clashing.columns, "token_ids_", "n_tokens", "decoded_"]
    assert all(r.decoded_ == (r.text or "") and r.n_tokens == len(r.token_ids_) and r.token_ids == 7 for r in encoded.collect())


def test_planes(spark, odd, none, tmp_path):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(planes.word_bpe_path())
    folder = f"file://{tmp_path}/planes"
    manifest = planes.write_files(spark, odd, planes.word_bpe_path(), folder, 2, planes=32, file_ids=100)
    rows = planes.read_files(spark, manifest, folder).collect()
    at, want = 0, []
    for i, t, _ in sorted(ODD, key=lambda r: (r[0] is not None, r[0] or 0, r[1] or "")):
        ids = np.array(library.encode(t or "", add_special_tokens=False).ids + [2], "<u4")
        want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
        at += len(ids)
    assert sorted(((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in rows), key=lambda r: r[1]) == want
    assert planes.read_files(spark, planes.write_files(spark, none, planes.word_bpe_path(), folder, 2), folder).count() == 0


def test_toxicity(spark, odd, none):
    labels = spark.createDataFrame([(3, 0, 1), (4, 1, None), (6, 1, 0), (None, 1, 1), (3, 0, 0)], "doc_id long, quality int, toxic int")
    scorer = toxicity.fit(spark, odd, labels)
    rows = toxicity.score(spark, odd, scorer).collect()
    assert len(rows) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows)
    assert all(r.held_out == (r.doc_id is not None and zlib.crc32(str(r.doc_id).encode()) % 5 == 0) for r in rows)
    unfit = toxicity.fit(spark, odd, labels.filter("false"))
    assert {r.score for r in toxicity.score(spark, odd, unfit).collect()} == {0.0}
    assert toxicity.drop_toxic(spark, odd, unfit).count() == len(ODD)
    assert toxicity.score(spark, none, scorer).count() == 0


def test_licenses(spark, odd, none):
    assert license_scan.scan_licenses(odd).count() == 0
    assert license_scan.scan_licenses(none).count() == 0
    noted = docs_of(spark, [(1, "Released under the MIT License. Released under the MIT License.", "a"), (None, "İ Released under the MIT License.", None)])
    got = sorted((str(r.doc_id), r.license, r.span_start, r.span_end, r.coverage) for r in license_scan.scan_licenses(noted).collect())
    assert [(g[0], g[1], g[4]) for g in got] == [("1", "MIT", 1.0), ("1", "MIT", 1.0), ("None", "MIT", 1.0)]
    assert [g[2:4] for g in got[:2]] == [(0, 30), (32, 62)]


def test_html(spark):
    rows = [(1, "http://h/a", None, 1), (2, None, "", 2), (None, "x", "<p>a<p>b &lt; c", 3), (3, "http://h/b", "<div>" * 3000 + "deep", 4), (3, "http://h/b", "<b", 5)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text int")
    got = sorted((str(r.page_id), r.text, r.n_chars) for r in html_text.extract(spark, pages).collect())
    assert got == [("1", "", 0), ("2", "", 0), ("3", "<b", 2), ("3", "deep", 4), ("None", "a b < c", 7)]
    assert html_text.extract(spark, pages.filter("false")).count() == 0


def test_topk(spark):
    rows = [(0, [0.5, 0.25]), (1, [0.5, 0.25]), (2, [0.5, 0.25]), (3, None), (4, [None, 1.0]), (5, [float("nan"), 1.0]), (6, [float("inf"), 0.0]), (7, [1.0]), (None, [1.0, 1.0]), (2, [0.5, 0.25]), (8, [])]
    clashing = "vec_id long, embedding array<float>, `rank` int, query_id string, score string, `row` int, x string"
    table = spark.createDataFrame([(*r, 1, "a", "b", 2, "c") for r in rows], clashing)
    vectors = topk.written_table(spark, topk.usable_vectors(table), "t")
    found = lambda v, q, k: [tuple(r) for r in topk.top_k(spark, v, q, k).orderBy("query_id", "rank").collect()]
    same = 128 * 128 + 64 * 64
    # rows that repeat an id are candidates of their own; an empty vector scores 0
    assert found(vectors, vectors.filter("vec_id = 0"), 5) == [(0, 1, 7, 128 * 256), (0, 2, 1, same), (0, 3, 2, same), (0, 4, 2, same), (0, 5, 8, 0)]
    assert len(found(vectors, vectors.filter("vec_id = 2"), 9)) == 2 * 5
    assert found(vectors, vectors.filter("vec_id = 8"), 1) == [(8, 1, 0, 0)]
    assert found(vectors.filter("false"), vectors, 5) == [] == found(vectors, vectors.filter("false"), 5)


def test_topk_of_large_components(spark):
    """Finite components of any size take part; sums beyond a bigint show as the nearest one."""
    rows = [(0, [2000000.0, 1.0]), (1, [2000000.0, 2.0]), (2, [1e30, 0.0]), (3, [-1e30, 5.0]), (4, [1.0, 1.0]), (5, [1e308, 1.0]), (6, [float(1 << 40), 1.0])]
    vectors = topk.written_table(spark, topk.usable_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")), "t")
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in topk.top_k(spark, vectors, vectors, 3).collect()}
    exact = {i: [int(e) * 256 for e in v] for i, v in rows}
    for q in exact:
        scores = {i: max(-(1 << 63), min((1 << 63) - 1, sum(a * b for a, b in zip(exact[q], v)))) for i, v in exact.items() if i != q}
        want = sorted(scores.items(), key=lambda p: (-p[1], p[0]))[:3]
        assert [got[q, k + 1] for k in range(3)] == want, q
