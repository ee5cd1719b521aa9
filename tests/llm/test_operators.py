"""The operators against brute force, the public libraries, SQL, and held-out rows."""

import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from subgraph_engine.llm import bpe, exact_dedup, html_text, license_scan, minhash, mixing, planes, registry, sharding, topk, toxicity


@pytest.mark.parametrize(("similarity", "least"), [(0.80, 0.99), (0.85, 0.995)])
def test_tables_find_planted_pairs(similarity, least):
    """Pairs whose shingle sets are just as similar share a table."""
    draw = np.random.Generator(np.random.PCG64(6))
    shingler, found, n = minhash.Shingler(5), 0, 1500
    for _ in range(n):
        size = int(draw.integers(30, 400))
        common = int(np.ceil(2 * size * similarity / (1 + similarity)))
        hashes = draw.integers(0, 2**64, 2 * size - common, dtype=np.uint64)
        a, b = (shingler.keys(np.sort(x)) for x in (hashes[:size], hashes[size - common :]))
        same = a == b
        found += same[: minhash.SIDE].any() and same[minhash.SIDE :].any()
    assert found / n >= least


def brute_components(docs, words, percent):
    sets = {}
    for i, text in docs:
        w = (text or "").encode().lower().split()
        sets[i] = {tuple(w[k : k + words]) for k in range(max(1, len(w) - words + 1))} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    having = {}
    for i, s in sets.items():
        for g in s:
            having.setdefault(g, []).append(i)
    for i, s in sets.items():
        common = {}
        for g in s:
            for j in having[g]:
                if j > i:
                    common[j] = common.get(j, 0) + 1
        for j, n in common.items():
            if 100 * n >= percent * (len(s) + len(sets[j]) - n):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(i)) for i in sets}


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL))
def test_same_as_sql(same_as_sql, name):
    same_as_sql(registry.QUERIES[name], registry.ORACLE_SQL[name])


def test_registry_has_all_ten():
    assert sorted(int(n[2:].split("_")[0]) for n in registry.QUERIES) == list(range(1, 11))


def test_minhash_on_documents(spark, sf_dir, duck):
    docs = duck.sql("SELECT doc_id, text FROM documents").fetchall()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in registry.QUERIES["op3_minhash"](spark, sf_dir).collect()}
    assert got == brute_components(docs, 4, 80)


@pytest.mark.parametrize("words", [4, 5])
def test_minhash_on_hot_groups(spark, words, monkeypatch):
    """A large group of near copies, not all near each other, and a passage that many texts share."""
    draw = random.Random(5)
    vocabulary = [f"w{k}" for k in range(4000)]
    base = [draw.choice(vocabulary) for _ in range(60)]
    passage = [draw.choice(vocabulary) for _ in range(55)]
    texts = []
    for _ in range(300):
        w = list(base)
        for _ in range(draw.choice([0, 1, 2, 3, 4, 6, 8])):
            w[draw.randrange(60)] = draw.choice(vocabulary)
        texts.append(" ".join(w))
    texts += [" ".join(passage + [draw.choice(vocabulary) for _ in range(draw.choice([3, 6, 10, 14, 20, 40]))]) for _ in range(200)]
    docs = list(enumerate(texts))
    monkeypatch.setattr(minhash, "TILE", 64)  # several tiles to a bucket
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(spark, frame, words, 80).collect()}
    assert got == brute_components(docs, words, 80)


@pytest.fixture(scope="module")
def table():
    return bpe.load_table(bpe.byte_bpe_path())


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(bpe.byte_bpe_path())


def encode(table, text, step):
    encoder, out = bpe.StreamEncoder(table), []
    for at in range(0, len(text), step):
        out += encoder.feed(text[at : at + step])
    return out + encoder.finish()


PARTS = ["a", "b", "the", "'s", " ", "  ", "\n", "1", "23", "!", "...", "<|endoftext|>", "<|endo", "é", "中", "🙂", "'", "ing", "\t", "z" * 7]


@given(st.lists(st.sampled_from(PARTS), max_size=300), st.sampled_from([1, 7, 50, 1000]))
@settings(max_examples=150, deadline=None)
def test_streamed_ids_are_the_library_s(table, library, parts, step):
    text = "".join(parts)
    before, bpe.PIECE_CHARS = bpe.PIECE_CHARS, 100  # buffers fill and overflow
    try:
        ids = encode(table, text, step)
    finally:
        bpe.PIECE_CHARS = before
    assert ids == library.encode(text, add_special_tokens=False).ids
    decoder = bpe.StreamDecoder(table)
    assert "".join(decoder.feed([i]) for i in ids) + decoder.finish() == text


@pytest.mark.parametrize("unit", ["a", " ", "1", "!", "é", "in", "the", "ACGT"])
def test_runs_without_end_keep_bounded_memory(table, library, unit):
    text = unit * 40_000
    run = bpe.RunEncoder(table)
    most, out = 0, []
    if unit.isalpha() and unit.isascii():
        for at in range(0, len(text), 1000):
            out += run.feed(text[at : at + 1000].encode())
            most = max(most, len(run.held))
        out += run.finish()
        assert most <= 2 * table.lookahead + 1000
        assert out == library.encode(text, add_special_tokens=False).ids
    assert encode(table, text, 5000) == library.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("unit", ["abcdefghij", "ACGT", "=", " ", "12"])
def test_pieces_of_documents_go_out_by_lookahead(table, library, unit, monkeypatch):
    """Documents of a few thousand characters with a long run: ids come before the run ends, and little is held."""
    runs, real = [], bpe.RunEncoder
    monkeypatch.setattr(bpe, "RunEncoder", lambda t: runs.append(real(t)) or runs[-1])
    text = f"before {unit * (8000 // len(unit))} after it"
    encoder, early = bpe.StreamEncoder(table), 0
    for piece in bpe._pieces(text[: len(text) - 9]):
        early += len(encoder.feed(piece))
        held = len(encoder.held) + sum(len(r.held) for r in runs)
        assert held <= 2 * bpe.PIECE_CHARS + 2 * table.lookahead
    assert runs or early
    ids = [i for some in bpe.encode_stream(table, bpe._pieces(text)) for i in some]
    assert ids == library.encode(text, add_special_tokens=False).ids


def test_lookahead_is_finite_and_proper(table):
    assert table.proper and 0 < table.lookahead < 10_000


@given(st.lists(st.integers(0, 2**32 - 1), max_size=400), st.sampled_from([4, 32]))
@settings(max_examples=80, deadline=None)
def test_planes_round_trip(ids, planes_per_id):
    array = np.array(ids, "<u4")
    if len(array):
        parts = planes.pack_chunk(array, planes_per_id)
        assert (planes.unpack_chunk(parts, len(array)) == array).all()
    writer = planes.PlaneWriter(planes_per_id, chunk_ids=64)
    cuts = [0, len(ids) // 3, len(ids) // 2, len(ids)]
    docs = [(k if k else None, array[a:b]) for k, (a, b) in enumerate(zip(cuts, cuts[1:]))]
    for doc, part in docs:
        writer.add(doc, part)
    back = list(planes.PlaneReader(pa.BufferReader(writer.finish())).documents())
    assert [d for d, _ in back] == [d for d, _ in docs]
    assert all((a == b).all() for (_, a), (_, b) in zip(back, docs))


def test_word_encoder_is_the_library(duck):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(planes.word_bpe_path())
    encoder, end = planes.WordEncoder(planes.word_bpe_path()), np.array([2], "<u4").tobytes()
    texts = [t or "" for (t,) in duck.sql("SELECT text FROM documents").fetchall()]
    texts += ["It's <|endoftext|> <|ENDOFTEXT|> ΣΑΣ İx é ẛ̣", "a\x0bb\x1cc\xa0d", "''s 12é", "\U00011de0 x"]
    for text in texts:
        assert encoder.encode(text, end).tolist() == library.encode(text, add_special_tokens=False).ids + [2]


def test_files_of_documents(spark, sf_dir, duck):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(planes.word_bpe_path())
    at, want = 0, {}
    for i, text in duck.sql("SELECT doc_id, text FROM documents ORDER BY doc_id").fetchall():
        ids = np.array(library.encode(text or "", add_special_tokens=False).ids + [2], "<u4")
        want[i] = (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    got = {r.doc_id: (r.start, r.n_tokens, r.ids_crc32) for r in registry.QUERIES["op10_planes"](spark, sf_dir).collect()}
    assert got == want


def test_digests_of_documents(spark, sf_dir, duck, library):
    want = {}
    for i, text in duck.sql("SELECT doc_id, text FROM documents").fetchall():
        ids = library.encode(text or "", add_special_tokens=False).ids
        want[i] = (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((text or "").encode()).hexdigest())
    rows = registry.QUERIES["op5_bpe"](spark, sf_dir).collect()
    assert {r.doc_id: (r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in rows} == want


def best_of(vectors, q, k=5):
    """By a full sort of Python integers."""
    scores = [(-int(vectors[i].astype(object) @ vectors[q].astype(object)), i) for i in range(len(vectors)) if i != q]
    return [(i, -s) for s, i in sorted(scores)[:k]]


def test_index_stops_early_and_is_exact():
    draw = np.random.Generator(np.random.PCG64(3))
    vectors = np.floor(256 * draw.normal(0, 0.12, (3000, 48)))
    vectors[100:400] = vectors[100]  # ties
    rows = np.arange(3000)
    index = topk.BlockIndex(rows, rows, vectors)
    early = 0
    for q in range(0, 3000, 60):
        early += len(index._possible(vectors[q], 5, np.array([q]), -np.inf)) < 3000
        want = best_of(vectors, q)
        assert list(zip(*(x.tolist() for x in index.search(q, vectors[q], 5)))) == want
        floor = float(want[-1][1])  # a bar that is known before keeps the members
        assert list(zip(*(x.tolist() for x in index.search(q, vectors[q], 5, floor)))) == want
        assert not len(index.search(q, vectors[q], 5, 1e18)[0])
    assert early > 10


def test_index_with_large_components():
    draw = np.random.Generator(np.random.PCG64(4))
    vectors = draw.integers(-(1 << 20), 1 << 20, (700, 9)).astype(float)
    index = topk.BlockIndex(np.arange(700), np.arange(700), vectors)
    assert index.shift > 0
    for q in range(0, 700, 50):
        assert list(zip(*(x.tolist() for x in index.search(q, vectors[q], 5)))) == best_of(vectors, q)


def test_blocks_and_tiles_do_not_change_results(spark, sf_dir):
    vectors = topk.written_table(spark, topk.usable_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet")), "t")
    queries = vectors.filter("vec_id % 50 = 0")
    whole = sorted(map(tuple, topk.top_k(spark, vectors, queries).collect()))
    assert whole == sorted(map(tuple, topk.top_k(spark, vectors, queries, rows=64, tile=3).collect()))


def test_mixture_comes_near_its_targets(spark, sf_dir):
    rows = mixing.mix(spark, spark.read.parquet(f"{sf_dir}/documents.parquet")).collect()
    assert all(r.taken <= 2 * r.size for r in rows)
    by_source = {}
    for r in rows:
        by_source.setdefault(r.source, [r.source_size, r.target, 0, 0])
        by_source[r.source][2] += r.taken
        by_source[r.source][3] = max(by_source[r.source][3], r.size)
    assert all(abs(taken - target) <= max(largest, 0.1 * target) for _, target, taken, largest in by_source.values())
    assert all(target <= 2 * size + 1e-6 for size, target, *_ in by_source.values())
    total = sum(size for size, *_ in by_source.values())
    assert abs(sum(target for _, target, *_ in by_source.values()) - 1.5 * total) < 1e-3 * total


def test_every_offset_keeps_near_the_targets(spark, sf_dir):
    """One offset is drawn; over many seeds the copies of a source are what is expected."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").cache()
    offsets = [mixing.offset(seed) for seed in range(400)]
    assert all(0 <= u < 1 for u in offsets) and abs(sum(offsets) / 400 - 0.5) < 0.05
    expected, mean = {}, {}
    for seed in range(6):
        for r in mixing.mix(spark, docs, seed=seed).collect():
            mean[r.source] = mean.get(r.source, 0) + r.taken / 6
            expected[r.source] = r.target
    assert all(abs(mean[s] - t) < 0.12 * t + 50 for s, t in expected.items())


def test_targets_by_repeated_dealing(spark):
    """The closed form against dealing the excess again and again."""
    draw = random.Random(8)
    for _ in range(4):
        sizes = {f"s{k:02d}": draw.choice([0, 5, 50, 500, 5000]) for k in range(draw.randint(1, 9))}
        weight = {s: (3, 1, 2)[k % 3] for k, s in enumerate(sorted(sizes))}
        target, left, open_sources = dict.fromkeys(sizes, 0.0), 1.5 * sum(sizes.values()), set(sizes)
        while left > 1e-9 and open_sources:
            total = sum(weight[s] for s in open_sources)
            share = {s: left * weight[s] / total for s in open_sources}
            left = 0.0
            for s in list(open_sources):
                target[s] += share[s]
                if target[s] >= 2 * sizes[s]:
                    left += target[s] - 2 * sizes[s]
                    target[s] = 2 * sizes[s]
                    open_sources.discard(s)
        frame = spark.createDataFrame(list(sizes.items()), "source string, source_size long")
        got = {r.source: r.target for r in mixing.targets(frame).collect()}
        assert all(abs(got[s] - target[s]) < 1e-6 * (1 + target[s]) for s in sizes)


def test_emitted_copies(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    copies = {r.doc_id: r.copies for r in mixing.mix(spark, docs).collect()}
    seen = {r.doc_id: r["count"] for r in mixing.emit(spark, docs).groupBy("doc_id").count().collect()}
    assert seen == {i: n for i, n in copies.items() if n}


def test_every_shard_has_the_mixture(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = sharding.shard_rows(spark, docs, 4).collect()
    share = {}
    for r in rows:
        share.setdefault(r.source, [0] * 4)[r.shard] += 1
    assert all(max(n) - min(n) <= 3 for n in share.values())
    sizes = [sum(n[k] for n in share.values()) for k in range(4)]
    assert max(sizes) - min(sizes) <= 1
    again = sharding.shard_rows(spark, docs.repartition(7), 4).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again))


@pytest.mark.parametrize("shards", [1, 4, 16, 700])
def test_shards_by_plain_python(spark, sf_dir, duck, shards):
    """Seeded ranks within sources, fractions, one order, equal cuts: by lists."""
    rows = duck.sql("SELECT doc_id, source, text FROM documents").fetchall() + [(None, None, None), (None, "src1", "x"), (5, None, "")]
    docs = spark.createDataFrame(rows, "doc_id long, source string, text string")
    held = []
    for i, source, text in rows:
        crc = zlib.crc32((text or "").encode())
        mixed = hashlib.md5(":".join(str(x) for x in (sharding.SEED, i, crc) if x is not None).encode()).hexdigest()
        held.append((source, mixed, (i is not None, i or 0), i, crc, len((text or "").encode()) + 1))
    ordered = []
    for source in {h[0] for h in held}:
        own = sorted(h for h in held if h[0] == source) if source is not None else sorted((h for h in held if h[0] is None), key=lambda h: h[1:3])
        ordered += [((k + 0.5) / len(own), source is None, source or "", *h[1:]) for k, h in enumerate(own)]
    ordered.sort(key=lambda h: h[:5])
    small, longer = divmod(len(rows), shards)
    want, at = [], 0
    for shard in range(shards):
        for slot in range(small + (shard < longer)):
            *_, i, crc, size = ordered[at]
            want.append((i, size, crc, shard, slot))
            at += 1
    got = [(r.doc_id, r.size, r.text_crc32, r.shard, r.slot) for r in sharding.shard_rows(spark, docs, shards).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)


def test_written_shards(spark, sf_dir, tmp_path):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    sharding.write_shards(spark, docs, 3, f"{tmp_path}/shards")
    back = spark.read.parquet(f"{tmp_path}/shards")
    assert back.count() == docs.count() and back.select("shard").distinct().count() == 3


def test_toxic_words_are_found_in_rows_held_out(spark, sf_dir):
    """Invented texts: ordinary words, and stems that only toxic texts hold, with endings not seen before."""
    draw = random.Random(2)
    syllables = ["an", "er", "on", "th", "in", "re", "at", "ou", "st", "ed"]
    word = lambda: "".join(draw.choice(syllables) for _ in range(draw.randint(1, 4)))
    rows, labels = [], []
    for i in range(1500):
        toxic = i % 8 == 0
        words = [word() for _ in range(draw.choice([8, 40, 200, 900]))]
        for _ in range(draw.randint(1, 4) if toxic else 0):
            words.insert(draw.randrange(len(words)), draw.choice(["zorgle", "blimf"]) + (word() if draw.random() < 0.5 else ""))
        rows.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    scorer = toxicity.fit(spark, docs, spark.createDataFrame(labels, "doc_id long, toxic int"))
    truth = dict(labels)
    held = [r for r in toxicity.score(spark, docs, scorer).collect() if r.held_out]
    assert len(held) > 200
    assert sum(r.predicted == truth[r.doc_id] for r in held) / len(held) > 0.97
    assert scorer.score("") < 0.5 and scorer.score("zorgle zorglexyz") > 0.5


def test_toxicity_ignores_held_out_labels(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    from pyspark.sql import functions as F

    turned = labels.withColumn("toxic", F.when(toxicity.fold() == 0, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = (toxicity.fit(spark, docs, x) for x in (labels, turned))
    assert a.model == b.model and np.allclose(a.weights, b.weights)


def test_toxicity_counts_do_not_stop_at_the_sample(spark, monkeypatch):
    """Counts are of all labelled rows and types of all documents; a model too large for a broadcast scores alike."""
    draw = random.Random(5)
    name = lambda n: "".join(draw.choice("abcdefgh") for _ in range(n))
    # each toxic form is in three texts alone, so a sample misses most of them
    forms = ["zz" + name(7) for _ in range(100)]
    rows = [(i, " ".join([*(name(2) for _ in range(20)), *([forms[i // 2 % 100]] if i % 2 else [])]), i % 2) for i in range(600)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, t) for i, _, t in rows], "doc_id long, toxic int")
    counted = {form for i, text, t in rows if t and zlib.crc32(str(i).encode()) % 5 in (1, 2, 3) for form in text.split()[20:]}
    scorer = toxicity.fit(spark, docs, labels, rows=60)
    keys = toxicity.word_keys([f"n{form}$" for form in sorted(counted)])
    assert len(counted) > 90 and scorer.model[0].find(keys)[2].all()
    more = docs.unionByName(spark.createDataFrame([(1000 + k, f"zz{name(9)}") for k in range(200)], docs.schema))
    assert toxicity.fit(spark, more, labels, rows=60).model != scorer.model
    found = {r.doc_id: r.score for r in toxicity.score(spark, docs, scorer).collect()}
    monkeypatch.setattr(toxicity, "BROADCAST_ENTRIES", 10)
    large = toxicity.fit(spark, docs, labels, rows=60)
    assert large.table is not None and np.allclose(large.weights, scorer.weights)
    assert {r.doc_id: r.score for r in toxicity.score(spark, docs, large).collect()} == pytest.approx(found)
    assert toxicity.drop_toxic(spark, docs, large).count() == sum(s < 0.5 for s in found.values())


def test_large_toxicity_models_are_passed_over(spark, monkeypatch):
    """Texts were joined with all rows of the model that they might need, dozens of times their size."""
    import pyarrow as pa
    from subgraph_engine.storage import qualified

    draw = random.Random(8)
    rows = [(i, " ".join(draw.choice("aa bb cc dd abcd abcde bad worse".split()[: 6 + 2 * (i % 2)]) for _ in range(30)), i % 2) for i in range(200)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, t) for i, _, t in rows], "doc_id long, toxic int")
    small = toxicity.fit(spark, docs, labels)
    monkeypatch.setattr(toxicity, "BROADCAST_ENTRIES", 10)
    large = toxicity.fit(spark, docs, labels)
    plan = toxicity.drop_toxic(spark, docs, large)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan
    texts = [t for _, t, _ in rows] + [None, "", "new words abc", "bad"]
    batches = [pa.RecordBatch.from_pydict({"text": pa.array(texts[at : at + 9], pa.string())}) for at in range(0, len(texts), 9)]
    for name, bound in (("FILE_ROWS", 7), ("SCORED_WORDS", 40)):
        monkeypatch.setattr(toxicity, name, bound)
    for held in (0, 1 << 18):
        monkeypatch.setattr(toxicity, "HELD_TOKENS", held)
        found = list(toxicity.Scorer().ratios_by_files(iter(batches), qualified(spark, large.table._shared_path)))
        assert [b.num_rows for b, _ in found] == [b.num_rows for b in batches]
        assert np.concatenate([r for _, r in found]) == pytest.approx(small.ratios(texts))


def test_toxicity_takes_texts_apart_in_slices(monkeypatch):
    """Batches of 16 MB were taken apart whole, which took hundreds of MB of an executor."""
    import pyarrow as pa

    batch = pa.RecordBatch.from_pydict({"text": pa.array(["some words " * 20] * 50 + [None, "x" * 5000], pa.string())})
    monkeypatch.setattr(toxicity, "SLICE_BYTES", 2000)
    parts = list(toxicity.slices(iter([batch, batch.slice(0, 0)])))
    assert len(parts) > 5 and pa.Table.from_batches(parts).combine_chunks().to_batches() == [batch]


def test_toxicity_reads_words_as_arrays(spark):
    """Words were hashed and numbered one by one, which took more than half of op6's time."""
    import pyarrow as pa
    from pyspark.sql import functions as F
    from subgraph_engine.llm.hashing import string_hash

    draw = random.Random(4)
    words = ["".join(draw.choice("abcé\u4e00\U0001d400") for _ in range(n)) for n in [*range(45)] * 3]
    table = spark.createDataFrame([(k, w) for k, w in enumerate(words)], "k int, w string")
    want = [r.h for r in table.orderBy("k").select(F.xxhash64("w").alias("h")).collect()]
    assert string_hash(pa.array(words)).tolist() == want
    assert string_hash(pa.array(words).slice(5, 90)).tolist() == want[5:95] and not len(string_hash(pa.array([], pa.string())))
    texts = ["don't a.b x_1 Größe² the2the ...", "", None, "ﬁ ①② ñandú-x", "plain words. Don t", "1 2 3", "plain the the"]
    lexicon = toxicity.Lexicon()
    for part in (texts[:2], texts[2:], texts):
        numbers, ends = lexicon.read(part)
        found = lexicon.words().take(pa.array(numbers)).to_pylist()
        assert [found[a:b] for a, b in zip([0, *ends], ends)] == [toxicity.WORD.findall((t or "").lower()) for t in part]
    assert len(set(lexicon.words().to_pylist())) == len(lexicon) and lexicon.words(3).to_pylist() == lexicon.words().to_pylist()[3:]
    assert toxicity.word_keys(lexicon.words()).tolist() == lexicon.keys.tolist()


def brute_toxicity(rows, labels):
    """The ratio of any text by dictionaries, from the definition."""
    import math
    from collections import Counter, defaultdict

    split = lambda t: toxicity.WORD.findall((t or "").lower())
    known = {i: t for i, t in labels if zlib.crc32(str(i).encode()) % 5 in (1, 2, 3)}
    held, places, contexts, nodes = [Counter(), Counter()], [Counter(), Counter()], [defaultdict(set), defaultdict(set)], [Counter(), Counter()]
    everything = {w for _, text in rows for w in split(text)}
    path = lambda w: ["", *(w[:k] for k in toxicity.STEMS if k < len(w)), w + "$"]
    for i, text in rows:
        if i in known:
            words = split(text)
            held[known[i]].update(set(words))
            places[known[i]].update(words)
            for k in range(1, len(words)):
                contexts[known[i]][words[k - 1], words[k]].add(words[k - 2] if k > 1 else None)
    children = defaultdict(set)
    for w in everything:
        for a, b in zip(path(w), path(w)[1:]):
            children[a].add(b)
            for c in (0, 1):
                nodes[c][b] += held[c][w]
    frequent = {w for w in everything if held[0][w] + held[1][w] >= toxicity.PAIR_DOCUMENTS}
    above = [Counter(), Counter()]
    for c in (0, 1):
        for pair, seen in contexts[c].items():
            if set(pair) <= frequent and len(seen) > toxicity.PAIR_DISCOUNT:
                above[c][pair] = len(seen) - toxicity.PAIR_DISCOUNT

    def likelihood(c, w):
        total = 0.0
        for a, b in zip(path(w), path(w)[1:]):
            kids = children[a]
            m = [sum(nodes[k][x] for x in kids) for k in (0, 1)]
            t = [sum(nodes[k][x] > 0 for x in kids) for k in (0, 1)]
            freed = toxicity.DISCOUNT * t[c] / m[c] if m[c] else 1.0
            if not nodes[0][b] and not nodes[1][b]:
                total += math.log(freed)
                continue
            shared = ((nodes[0][b] > 0) + (nodes[1][b] > 0) + 1.5) / (sum(t) + len(kids) + 1)
            own = max(nodes[c][b] - toxicity.DISCOUNT, 0) / m[c] if m[c] else 0.0
            total += math.log(own + freed * shared)
        return total

    def step(c, before, w):
        base = likelihood(c, w)
        if before is None:
            return base
        n = places[c][before]
        left = 1 - sum(k for (h, _), k in above[c].items() if h == before) / n if n else 1.0
        both = (before, w) in above[0] or (before, w) in above[1]
        return math.log(above[c][before, w] / n + left * math.exp(base)) if both and n else base + math.log(left)

    def ratio(text):
        words = split(text)
        return max((step(1, h, w) - step(0, h, w) for h, w in zip([None, *words], words)), default=0.0)

    return ratio


def test_toxicity_by_dictionaries(spark):
    """Words, stems, pairs and unseen forms; pairs that copies repeat do not count as frequent."""
    draw = random.Random(9)
    words = ["the", "of", "market", "marketing", "dog", "idiot", "idiotic", "very", "ab", "é", "straße"]
    rows, labels = [], []
    for i in range(160):
        text = " ".join(draw.choice(words[:5] + words[8:]) for _ in range(12))
        if i % 4 == 0:
            text += f" {draw.choice(words)} very {draw.choice(['idiot', 'idiotic'])} {draw.choice(words)}."
        rows.append((i, text if i % 10 else "the market of the very dog"))
        labels.append((i, int(i % 4 == 0)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    scorer = toxicity.fit(spark, docs, spark.createDataFrame(labels, "doc_id long, toxic int"))
    ratio = brute_toxicity(rows, labels)
    asked = [t for _, t in rows] + ["", None, "idiotically", "xyz", "very very", "The very idiot's dog, straße"]
    assert scorer.ratios(asked) == pytest.approx([ratio(t) for t in asked], abs=1e-4)


def test_toxicity_pairs_of_words_in_few_documents(spark):
    """Pairs of words that fewer than four documents hold were left out, however many contexts they have."""
    rows = [(i, "plain words of many kinds") for i in range(60)]
    counted = [i for i in range(60) if zlib.crc32(str(i).encode()) % 5 in (1, 2, 3)][:2]
    for i in counted:
        rows[i] = (i, " ".join(f"c{'abcdef'[k]}{'xy'[i == counted[0]]} rare pair" for k in range(6)))
    labels = [(i, int(i in counted or i % 7 == 0)) for i in range(60)]
    scorer = toxicity.fit(spark, spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int"))
    rare, pair = toxicity.word_keys(["rare", "pair"])
    assert scorer.model[2].find(toxicity.long_hash(np.array([rare])) ^ pair)[2].all()
    asked = ["the rare pair", "rare plain pair", rows[counted[0]][1]]
    assert scorer.ratios(asked) == pytest.approx([brute_toxicity(rows, labels)(t) for t in asked], abs=1e-4)


def test_toxicity_compares_whole_texts(spark, monkeypatch):
    """Scores were of the highest word alone, and of passages of just so many words where more were asked for."""
    draw = random.Random(3)
    # no word tells alone: texts differ by how many of their words lean to one class
    mild, plain = [f"mild{c}xx" for c in "abcdefghijklmnop"], [f"base{c}yy" for c in "abcdefghijklmnop"]
    rows = [(i, " ".join(draw.choice(mild if draw.random() < (0.7 if i % 2 else 0.3) else plain) for _ in range(60))) for i in range(400)]
    labels = [(i, i % 2) for i, _ in rows]
    scorer = toxicity.fit(spark, spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, toxic int"))
    texts = [t for _, t in rows] + ["", None, "mildaxx"]
    highest, whole = scorer.measures(texts)
    steps = [scorer._steps(*scorer.lexicon.read([t])).tolist() for t in texts]
    assert whole == pytest.approx([sum(s) / len(s) if s else 0.0 for s in steps])
    assert highest == pytest.approx([max(s, default=0.0) for s in steps])
    held = [k for k, (i, _) in enumerate(rows) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert sum((scorer.scores([rows[k][1]])[0] >= 0.5) == labels[k][1] for k in held) / len(held) > 0.9
    monkeypatch.setattr(toxicity, "PASSAGE", 3)
    means = [[sum(s[a:b]) / (b - a) for a in range(len(s)) for b in range(a + min(3, len(s)), len(s) + 1)] for s in steps[:20] + steps[-3:]]
    assert scorer.ratios(texts[:20] + texts[-3:]) == pytest.approx([max(m, default=0.0) for m in means])


def page(body, url="http://site/x"):
    return html_text.Page(body).main_text(frozenset(), html_text.host_of(url))


def test_main_text():
    assert page("<nav>menu</nav><article><h1>T &amp; t</h1><p>a <b>b</b>c<br>d<p>e&nbsp;f</article><footer>z</footer>") == "T & t a bc d e f"
    assert page("<div id=sidebar>x</div><p>one<div class='cookie-notice'>ok</div><p>two<script>var a = '</p>';</script>") == "one two"
    assert page("<article>text<section id=comments><p>reader</section><form>f</form><div class=ad>buy</div> end</article>") == "text end"
    assert page("<body><p>x <!-- <p>no --> y</p><ul><li>1<li>2</ul><table><tr><td>a<td>b</table>") == "x y 1 2 a b"
    assert page("<main><header><h1>Title</h1></header><p>body</main><header>site</header>") == "Title body"


def test_templates_of_sections_and_in_articles(spark):
    """A block on a tenth of a host's pages is a template, so is a paragraph of the article on most; rare ones stay."""
    def body(k):
        box = "<div class=x1>Join our section today</div>" if k % 10 == 0 else ""
        rare = "<div class=x2>Only here and there</div>" if k % 100 < 4 else ""
        once = "<h2>Results</h2>" if k % 10 == 1 else ""
        return f"<main>{once}<p>story number {k} of the day</p><p>All rights of this site are kept.</p>{box}{rare}</main>"

    pages = spark.createDataFrame([(k, "http://d.example/p", body(k)) for k in range(200)], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_text.extract(spark, pages).collect()}
    assert got[50] == "story number 50 of the day"
    assert got[2] == "story number 2 of the day Only here and there"
    assert got[11] == "Results story number 11 of the day"


def test_site_templates(spark):
    """A block that many different pages of a host have goes; copies of one article keep their text."""
    template = "<div class='promo-free'><span>Follow us everywhere</span></div>"
    rows = [(k, "http://a.example/p", f"<div><p>story number {k} of the day</p>{template}</div>") for k in range(12)]
    rows += [(100 + k, "http://b.example/p", "<div><div>the same text</div><p>everywhere</p></div>") for k in range(12)]
    rows += [(200, "http://c.example/p", f"<div><p>once</p>{template.replace('promo-free', 'x')}</div>")]
    pages = spark.createDataFrame([(i, u, h.replace("promo-free", "x1")) for i, u, h in rows], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_text.extract(spark, pages).collect()}
    assert got[3] == "story number 3 of the day"
    assert got[105] == "the same text everywhere"
    assert got[200] == "once Follow us everywhere"
    joined = html_text._extract_joined(pages, html_text.find_templates(spark, pages))
    assert {r.page_id: r.text for r in joined.collect()} == got


def unnamed(markup):
    """The page with neutral tags and class names."""
    import re

    for k, tag in enumerate(("nav", "footer", "article", "aside", "main", "header")):
        markup = re.sub(rf"<(/?){tag}\b[^>]*>", lambda m: f"</div>" if m[1] else f'<div class="k{k}">', markup)
    return re.sub(r'class="(ad|sidebar|comments?|cookie[^"]*|menu|newsletter)"', lambda m: f'class="z{len(m[1])}"', markup)


def test_recurrence_alone_separates_furniture(spark, sf_dir, duck):
    """Pages without telling tags or names on their own hosts: what goes, goes by counts."""
    import html
    import re

    rows = duck.sql(f"SELECT page_id, url, html FROM '{sf_dir.replace('sf0.001', 'sf0.1')}/pages.parquet'").fetchall()
    pages = spark.createDataFrame([(i, u, unnamed(h)) for i, u, h in rows], "page_id long, url string, html string")
    want = {i: " ".join(html.unescape(re.sub(r"<[^>]*>", " ", re.search(r"<article>(.*)</article>", h, re.S)[1])).split()) for i, _, h in rows}
    got = {r.page_id: r.text for r in html_text.extract(spark, pages).collect()}
    assert sum(got[i] == want[i] for i in want) >= 0.95 * len(want)
    # without the counts the furniture stays
    assert not any(html_text.Page(unnamed(h)).main_text(frozenset(), html_text.host_of(u)) == want[i] for i, u, h in rows[:200])


def test_templates_of_the_given_pages(spark, sf_dir):
    """Counting finds the hosts' menus, adverts and footers on the tables as they are."""
    pages = spark.read.parquet(f"{sf_dir.replace('sf0.001', 'sf0.1')}/pages.parquet")
    assert html_text.find_templates(spark, pages).count() > 0


def test_pages_against_their_articles(spark, sf_dir, duck):
    import html
    import re

    got = {r.page_id: r.text for r in registry.QUERIES["op4_html"](spark, sf_dir).collect()}
    for i, markup in duck.sql("SELECT page_id, html FROM pages").fetchall():
        article = re.search(r"<article>(.*)</article>", markup, re.S)[1]
        assert got[i] == " ".join(html.unescape(re.sub(r"<[^>]*>", " ", article)).split())


def test_dedup_levels_agree(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    a = {tuple(r) for r in exact_dedup.find_duplicates(spark, docs).collect()}
    b = {tuple(r)[:4] for r in exact_dedup.find_duplicates(spark, docs, digest=True).collect()}
    assert a == b
    assert exact_dedup.drop_duplicates(spark, docs).count() == sum(r[3] for r in a)


def brute_licenses(index, text):
    """Every template against the whole text, without fingerprints, chains or bands."""
    words = [index.number.get(w, 0) for w in license_scan.words_of(text or "")]
    found = []
    for t, template in enumerate(index.words):
        short = len(template) <= license_scan.SHORT
        best, before = [], [(0, 0, -1, -1)] * (len(words) + 1)
        for w in template:
            now = [(0, 0, -1, -1)]
            for j, own in enumerate(words):
                s, n, a, z = before[j]
                cell = (s + license_scan.MATCH, n + 1, j if n == 0 else a, j) if own == w else (s + license_scan.CHANGE, n, a, z)
                for other in (before[j + 1], now[j]):
                    gap = (other[0] + license_scan.GAP, *other[1:])
                    cell = gap if gap[:2] > cell[:2] else cell
                now.append(cell if cell[0] > 0 else (0, 0, -1, -1))
            best += [c for c in now if c[1]]
            before = now
        for score, matched, a, b in best:
            coverage = matched / (len(template) + b - a + 1 - matched)
            if coverage >= license_scan.COVERAGE if short else matched >= license_scan.PASSAGE and matched >= license_scan.COVERAGE * (b - a + 1):
                found.append((-score, index.names[t], a, b, matched))
    kept = []
    for match in sorted(found):
        if all(match[3] < a or match[2] > b for _, _, a, b, _ in kept):
            kept.append(match)
    return sorted((name, matched) for _, name, _, _, matched in kept)


def test_license_lines_of_documents(spark, sf_dir, duck):
    got = {}
    for r in registry.QUERIES["op7_licenses"](spark, sf_dir).collect():
        got.setdefault(r.doc_id, []).append((r.license, r.matched_words))
    lines = {"Released under the MIT License.": "MIT", "Licensed under CC BY-NC 4.0.": "CC-BY-NC-4.0", "Licensed under the Apache License, Version 2.0.": "Apache-2.0", "This work is licensed under the GNU General Public License, version 3.": "GPL-3.0"}
    for i, text in duck.sql("SELECT doc_id, text FROM documents").fetchall():
        want = sorted(name for line in (text or "").split("\n") for notice, name in lines.items() if notice in line)
        assert sorted(name for name, _ in got.get(i, [])) == want, i


def test_changed_license_notices():
    templates = license_scan.templates_of_files()
    index = license_scan.TemplateIndex(templates)
    scan = index.scan
    mit = templates["MIT"][-1].split("\n\n")[1]
    text = f"intro words here. {mit.replace('free of charge', 'free of any charge').replace('merge, ', '')} More words."
    ((name, coverage, matched, start, end),) = scan(text)
    assert name == "MIT" and 0.3 < coverage < 0.6 and matched > 60
    assert text[start:end].startswith("Permission") and text[start:end].endswith("conditions")
    assert [r[0] for r in scan("Licensed under CC BY 4.0. x y z Licensed under CC BY-NC 4.0.")] == ["CC-BY-4.0", "CC-BY-NC-4.0"]
    assert scan("a license to drive") == [] and scan("") == [] and scan(None) == []
    plain = lambda s: [(r[0], r[1] > 0.99) for r in scan(s)]
    assert plain("This work is licensed under the GNU Affero General Public License, version 3.") == [("AGPL-3.0", True)]
    assert plain("This work is licensed under the GNU General Public License, version 3.") == [("GPL-3.0", True)]
    assert plain("This work is licensed under the GNU Lesser General Public License, version 3.") == [("LGPL-3.0", True)]
    ((name, coverage, *_),) = scan("This work is licensed under the new GNU General Public License, version 2.")
    assert name == "GPL-2.0" and coverage < 0.95  # an inserted word costs
    third = templates["BSD-3-Clause"][-1].split("\n\n")[3]
    assert [r[0] for r in scan(third)] == ["BSD-3-Clause"]


def test_spans_are_of_the_text_as_it_is():
    scan = license_scan.TemplateIndex().scan
    for lead in ("İİİİ note. ", "ßẞ ", "plain "):
        text = f"{lead}Licensed under the MIT License. İ"
        ((name, coverage, _, start, end),) = scan(text)
        assert (name, coverage, text[start:end]) == ("MIT", 1.0, "Licensed under the MIT License")


@pytest.mark.parametrize("name", ["Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "BSL-1.0", "GPL-2.0", "GPL-3.0", "ISC", "LGPL-2.1", "LGPL-3.0", "MIT", "MPL-2.0", "Unlicense", "Zlib"])
def test_whole_texts_of_licenses(name):
    """Each text finds itself, also with lines left out and words changed."""
    templates = license_scan.templates_of_files()
    scan = license_scan._index(templates).scan
    text = templates[name][-1]
    assert max(scan(f"Some file. {text} The end."), key=lambda r: r[2])[:2] == (name, 1.0)
    words = text.split()
    changed = " ".join(w for k, w in enumerate(words) if k % 31) + " more"
    found = [r for r in scan(changed) if r[0] == name]
    assert sum(r[2] for r in found) > 0.85 * len(license_scan.words_of(text))


def test_licenses_by_whole_alignment():
    """Fingerprints, chains and bands find what an alignment of everything with everything finds."""
    templates = {k: v for k, v in license_scan.templates_of_files().items() if k in ("MIT", "ISC", "Zlib", "BSD-2-Clause", "BSD-3-Clause", "AGPL-3.0", "CC-BY-4.0", "CC-BY-NC-4.0")}
    index = license_scan.TemplateIndex(templates)
    mit, zlib_text = templates["MIT"][-1], templates["Zlib"][-1]
    samples = [
        "RELEASED UNDER the MIT license and licensed under the cc by 4.0",
        "x " * 30 + mit[: len(mit) // 2] + " y" * 20 + zlib_text[:300],
        mit.replace("without restriction", "with no restriction at all") + " tail " + "Licensed under CC BY-NC 4.0.",
        templates["BSD-3-Clause"][-1],
        "of the software and the use of the software in the public",
    ]
    for sample in samples:
        assert sorted((r[0], r[2]) for r in index.scan(sample)) == brute_licenses(index, sample), sample[:40]
