"""Near-duplicates by MinHash with tensored banding, verified on full shingle sets.

Instead of hashing for every table anew, two collections of ``SIDE`` short keys are
computed, each of ``WIDTH`` minhashes; a table's key is a pair of one key of each
collection. ``SIDE`` squared tables so cost twice ``SIDE`` keys. Texts at Jaccard 0.8
share none of the 144 tables with probability below 4 in 10,000, at 0.85 below 2 in 100,000.

1. Each text becomes the set of its shingles' 64-bit hashes. Texts with equal sets
   form a class; only one row of a class goes on.
2. Every bucket's smallest member is its leader; other members are verified
   against it, so a bucket of m members costs m - 1 comparisons. The diagonal
   tables (i-th key with i-th key) go first, and their links' components are
   found: links inside a component change nothing any more.
3. Of all tables, only buckets with members of several components go on. Short
   keys that no second class has are dropped before pairing, which leaves few
   rows for texts without relatives.
4. Buckets that are mixed even after their leaders' links are compared within,
   in tiles of bounded size and with a union-find that skips what is connected,
   so that no link that changes a component is lost. Only links leave a task.
5. Components of all links by star contraction.

Hot keys cost one partial-aggregate row per task, joins on them may be split.

Defined results: null texts and texts without words have no shingles and are linked with
nothing; fewer words than a shingle make one shingle of the whole sequence; a
null id never names a component that has another id; rows that repeat are linked
as copies; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.functions.components import star_components
from subgraph_engine.functions.sqltools import fresh
from subgraph_engine.storage import broadcast_if_few, release, text_batches, written_table

SIDE = 12
WIDTH = 3
SEED = 11
#: Rows and shingles in a chunk of a bucket; a lot of small buckets has about as many shingles.
TILE = 2048
TILE_SHINGLES = 1 << 20
WORD_CACHE = 1 << 16

SHINGLED = "doc_id long, n_shingles long, k1 long, k2 long"
KEYED = f"{SHINGLED}, a array<long>, b array<long>"
SETS = f"{SHINGLED}, shingles array<long>"
#: Keys of candidate texts are broadcast up to this many, 32 MB.
BROADCAST_KEYS = 1_000_000


class Shingler:
    """Shingle sets, set digests and the two collections of short keys of texts."""

    def __init__(self, words: int):
        self.words = words
        draw = np.random.Generator(np.random.PCG64(SEED))
        self.factors = draw.integers(1, 2**63, 2 * SIDE * WIDTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.mix = draw.integers(1, 2**63, WIDTH, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.cache: dict[bytes, int] = {}

    def _hash(self, word: bytes) -> int:
        found = xxhash.xxh64_intdigest(word, SEED)
        if len(self.cache) >= WORD_CACHE:
            self.cache.clear()
        if len(word) <= 64:
            self.cache[word] = found
        return found

    def shingles(self, text: str | None) -> np.ndarray:
        """Sorted distinct 64-bit hashes; bytes.lower and bytes.split act on ASCII alone."""
        words = (text or "").encode("utf-8", "surrogatepass").lower().split()
        if not words:
            return np.empty(0, np.uint64)
        cache = self.cache
        h = np.fromiter((cache[w] if w in cache else self._hash(w) for w in words), np.uint64, len(words))
        n = min(self.words, len(h))
        out = np.full(len(h) - n + 1, n, np.uint64)
        for k in range(n):
            out = (out ^ h[k : len(h) - n + 1 + k]) * np.uint64(0x9E3779B97F4A7C15)
            out ^= out >> np.uint64(29)
        return np.unique(out)

    def keys(self, shingles: np.ndarray) -> np.ndarray:
        least = np.empty(len(self.factors), np.uint64)
        for at in range(0, len(shingles), 4096):  # bounds the matrix for long texts
            part = (shingles[at : at + 4096, None] * self.factors).min(axis=0)
            least = part if at == 0 else np.minimum(least, part)
        mixed = (least.reshape(-1, WIDTH) >> np.uint64(7)) * self.mix
        return np.bitwise_xor.reduce(mixed ^ (mixed >> np.uint64(31)), axis=1)


def shingle_rows(docs: DataFrame, words: int, sets: bool = False) -> DataFrame:
    """A row per document: size and digest of its shingle set, and its short keys or the set itself."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Shingler(words)
        long, many = pa.int64(), pa.list_(pa.int64())
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                n, k1, k2, lists = [], [], [], ([], [])
                for text in batch.column("text").to_pylist():
                    s = own.shingles(text)
                    digest = np.frombuffer(hashlib.blake2b(s.tobytes(), digest_size=16).digest(), np.int64)
                    n.append(len(s))
                    k1.append(int(digest[0]))
                    k2.append(int(digest[1]))
                    if sets:
                        lists[0].append(s.view(np.int64))
                    else:
                        keys = own.keys(s).view(np.int64) if len(s) else np.empty(0, np.int64)
                        lists[0].append(keys[:SIDE])
                        lists[1].append(keys[SIDE:])
                columns = [batch.column("doc_id"), *(pa.array(c, long) for c in (n, k1, k2)), *(pa.array(c, many) for c in lists[: 1 if sets else 2])]
                names = ["doc_id", "n_shingles", "k1", "k2", *(["shingles"] if sets else ["a", "b"])]
                yield pa.RecordBatch.from_arrays(columns, names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, SETS if sets else KEYED)


def _sets_of(spark: SparkSession, docs: DataFrame, nodes: DataFrame, wanted: DataFrame, words: int) -> DataFrame:
    """node, n_shingles, shingles of the wanted nodes, shingled again from their texts.

    Only texts with a candidate are read here, so full sets are never stored for
    all documents.
    """
    few = nodes.join(wanted, "node", "left_semi").select("node", "doc_id", "k1", "k2")
    few = broadcast_if_few(written_table(spark, few, "minhash-wanted"), BROADCAST_KEYS)
    texts = docs.select(F.col("doc_id").cast("long"), "text")
    ids = few.select(F.col("doc_id").alias("_id")).distinct()
    texts = texts.join(broadcast_if_few(ids, BROADCAST_KEYS), F.col("doc_id").eqNullSafe(F.col("_id")), "left_semi")
    made = shingle_rows(texts, words, sets=True).drop("doc_id")
    return written_table(spark, made.join(few.drop("doc_id"), ["k1", "k2"]).select("node", "n_shingles", "shingles"), "minhash-sets")


def _similar(percent: int, common: Column, n: Column, m: Column) -> Column:
    return 100 * common >= percent * (n + m - common)


def near_duplicates(spark: SparkSession, docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row per document."""
    rows = _components(spark, docs, words, percent)
    return rows.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"))


def _components(spark: SparkSession, docs: DataFrame, words: int, percent: int) -> DataFrame:
    text_batches(spark)
    made = shingle_rows(docs, words).withColumn("row", F.monotonically_increasing_id())
    made = written_table(spark, made, "minhash-rows")
    classes = made.filter("n_shingles > 0").groupBy("k1", "k2").agg(F.min("row").alias("node"))
    classes = written_table(spark, classes, "minhash-classes")
    nodes = made.join(classes.select("node"), F.col("row") == F.col("node"), "left_semi").withColumnRenamed("row", "node")
    nodes = written_table(spark, nodes, "minhash-nodes")
    # first the diagonal tables, which join most relatives, then all, where a bucket is still mixed
    links = _linked(spark, docs, nodes, _diagonal_pairs(nodes), words, percent)
    parts = _parts(spark, links)
    paired = written_table(spark, _short_keys(nodes), "minhash-short")
    mixed = written_table(spark, _mixed_buckets(paired, parts), "minhash-mixed")
    if not mixed.isEmpty():
        pairs = mixed.filter("component <> leader_component").select("node", "leader").distinct()
        links = links.unionByName(_linked(spark, docs, nodes, pairs, words, percent))
        parts = _parts(spark, links)
        held = written_table(spark, _still_mixed(mixed, parts), "minhash-held")
        if not held.isEmpty():
            sets = _sets_of(spark, docs, nodes, held.select("node").distinct(), words)
            more = written_table(spark, _within(held, sets, percent), "minhash-more")
            release(spark, sets, held)
            parts = _parts(spark, links.unionByName(more))
    release(spark, nodes, paired, mixed)
    light = made.select("row", "doc_id", "n_shingles", "k1", "k2")
    named = light.join(classes, ["k1", "k2"], "left").withColumn(
        "node", F.when(F.col("n_shingles") > 0, F.col("node")).otherwise(F.col("row"))
    )
    named = named.join(parts.withColumnRenamed("vid", "node"), "node", "left")
    named = named.select("doc_id", "n_shingles", "row", F.coalesce("component", "node").alias("part"))
    named = written_table(spark, named, "minhash-named")
    release(spark, made, classes, parts)
    # most components are single rows: only those with several need a lookup
    names = named.groupBy("part").agg(F.min("doc_id").alias("component_id"), F.count(F.lit(1)).alias("_n")).filter("_n > 1")
    names = broadcast_if_few(written_table(spark, names, "minhash-names"), BROADCAST_KEYS)
    return named.join(names, "part", "left").select(
        "doc_id", "n_shingles", "row", F.when(F.col("_n") > 1, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id")
    )


def _parts(spark: SparkSession, links: DataFrame) -> DataFrame:
    return written_table(spark, star_components(spark, links, "minhash-parts"), "minhash-parts")


def _linked(spark: SparkSession, docs: DataFrame, nodes: DataFrame, pairs: DataFrame, words: int, percent: int) -> DataFrame:
    """src, dst of those pairs that full sets confirm, written."""
    pairs = written_table(spark, _of_like_size(nodes, pairs, percent), "minhash-pairs")
    ends = pairs.select("node").unionByName(pairs.select(F.col("leader").alias("node"))).distinct()
    sets = _sets_of(spark, docs, nodes, ends, words)
    links = written_table(spark, _verified(sets, pairs, percent), "minhash-links")
    release(spark, sets, pairs)
    return links


def _diagonal_pairs(nodes: DataFrame) -> DataFrame:
    """node, leader of the tables that pair the i-th keys of both sides."""
    tables = F.transform(F.arrays_zip("a", "b"), lambda z, i: F.xxhash64(i, z["a"], z["b"]))
    held = nodes.select("node", F.explode(tables).alias("bucket"))
    leaders = held.groupBy("bucket").agg(F.min("node").alias("leader"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    return held.join(leaders, "bucket").filter("node <> leader").select("node", "leader").distinct()


def _short_keys(nodes: DataFrame) -> DataFrame:
    """node, n_shingles, a, b: its keys of each side that some other class has too; none of a side leaves the node out."""
    side = lambda c: F.posexplode(c).alias("at", "key")
    own = ["node", "n_shingles"]
    short = nodes.select(*own, F.lit(0).alias("side"), side("a")).unionByName(nodes.select(*own, F.lit(1).alias("side"), side("b")))
    shared = short.groupBy("side", "at", "key").agg(F.count(F.lit(1)).alias("_n")).filter("_n > 1").drop("_n")
    short = short.join(shared, ["side", "at", "key"], "left_semi")
    keys = lambda s: F.collect_list(F.when(F.col("side") == s, F.xxhash64("at", "key")))
    paired = short.groupBy(*own).agg(keys(0).alias("a"), keys(1).alias("b"))  # at most SIDE keys each
    return paired.filter((F.size("a") > 0) & (F.size("b") > 0))


def _mixed_buckets(paired: DataFrame, parts: DataFrame) -> DataFrame:
    """bucket, node, component, n_shingles, leader, leader_component, n, mark, mark2, in_bucket: of all tables' buckets with several components."""
    own = paired.join(parts.withColumnRenamed("vid", "node"), "node", "left").withColumn("component", F.coalesce("component", "node"))
    node = ["node", "component", "n_shingles"]
    tables = own.select(*node, F.explode("a").alias("x"), "b").select(*node, "x", F.explode("b").alias("y"))
    tables = tables.select(*node, F.xxhash64("x", "y").alias("bucket"))
    buckets = tables.groupBy("bucket").agg(
        F.min("node").alias("leader"),
        F.min_by("component", "node").alias("leader_component"),
        F.count(F.lit(1)).alias("n"),
        F.min("component").alias("lo"),
        F.max("component").alias("hi"),
        F.bit_xor(F.xxhash64("node")).alias("mark"),
        F.bit_xor(F.xxhash64("node", F.lit(SEED))).alias("mark2"),
        F.sum("n_shingles").alias("in_bucket"),
    )
    return tables.join(buckets.filter("lo <> hi").drop("lo", "hi"), "bucket")


def _of_like_size(nodes: DataFrame, pairs: DataFrame, percent: int) -> DataFrame:
    """node, leader where the sizes allow the similarity."""
    n = nodes.select("node", F.col("n_shingles").alias("n"))
    m = nodes.select(F.col("node").alias("leader"), F.col("n_shingles").alias("m"))
    sized = pairs.join(n, "node").join(m, "leader")
    return sized.filter(100 * F.least("n", "m") >= percent * F.greatest("n", "m")).select("node", "leader")


def _verified(sets: DataFrame, pairs: DataFrame, percent: int) -> DataFrame:
    left = sets.select(F.col("node").alias("src"), F.col("n_shingles").alias("n"), F.col("shingles").alias("s"))
    right = sets.select(F.col("node").alias("dst"), F.col("n_shingles").alias("m"), F.col("shingles").alias("t"))
    both = pairs.select(F.col("node").alias("src"), F.col("leader").alias("dst")).join(left, "src").join(right, "dst")
    common = F.size(F.array_intersect("s", "t")).cast("long")
    return both.filter(_similar(percent, common, F.col("n"), F.col("m"))).select("src", "dst")


def _still_mixed(mixed: DataFrame, parts: DataFrame) -> DataFrame:
    """bucket, node, component, n_shingles, n, in_bucket of buckets of three and more that the leaders' links left in several components.

    Buckets of the same members are told by leader, size and 128 bits over their
    members' hashes; one of them stays.
    """
    held = mixed.filter("n > 2").drop("component").join(parts.withColumnRenamed("vid", "node"), "node", "left")
    held = held.withColumn("component", F.coalesce("component", "node"))
    name = ["n", "leader", "mark", "mark2", "in_bucket"]
    still = held.groupBy("bucket", *name).agg(F.min("component").alias("lo"), F.max("component").alias("hi"))
    still = still.filter("lo <> hi").groupBy(*name).agg(F.min("bucket").alias("bucket"))
    return held.select("bucket", "node", "component", "n_shingles").join(still.select("bucket", "n", "in_bucket"), "bucket")


def _within(held: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Links inside mixed buckets, in tiles of two chunks of the bucket each.

    Small buckets share a lot, which is one call; a tile of a large one is a lot
    by itself. Either way a lot is of bounded size.
    """
    total = held.agg(F.sum("n_shingles")).first()[0] or 0
    lots = max(1, total // TILE_SHINGLES)
    chunks = F.ceil(F.greatest(F.col("n") / F.lit(TILE), F.col("in_bucket") / F.lit(TILE_SHINGLES))).cast("int")
    held = held.withColumn("chunks", chunks).withColumn("chunk", F.pmod(F.xxhash64("node", F.lit(SEED)), F.col("chunks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))
    tiles = held.withColumn("other", other).select(
        "node", "component", "chunk", "chunks", "bucket", F.least("chunk", "other").alias("i"), F.greatest("chunk", "other").alias("j")
    )
    own = F.xxhash64("bucket", "i", "j")
    tiles = tiles.withColumn("lot", F.when(F.col("chunks") > 1, own).otherwise(F.pmod(F.xxhash64("bucket"), F.lit(lots))))
    tiles = tiles.withColumn("tile", own).drop("chunks", "bucket", "i", "j").join(sets, "node")

    def run(lot: pa.Table) -> pa.Table:
        lot = lot.sort_by("tile")
        tile = lot.column("tile").to_numpy()
        ends = [*np.flatnonzero(tile[1:] != tile[:-1]) + 1, len(tile)]
        src, dst = [], []
        for at, end in zip([0, *ends], ends):
            _tile_links(lot.slice(at, end - at), percent, src, dst)
        return pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64())})

    return tiles.groupBy("lot").applyInArrow(run, "src long, dst long")


def _tile_links(table: pa.Table, percent: int, src: list[int], dst: list[int]) -> None:
    """Adds links between rows of different components that connect something new.

    Rows of small components go first; what is left when only one component
    remains needs no comparison.
    """
    _, same, often = np.unique(table.column("component").to_numpy(), return_inverse=True, return_counts=True)
    order = np.lexsort((same, often[same]))
    table = table.take(pa.array(order))
    nodes, component = table.column("node").to_numpy(), table.column("component").to_pylist()
    chunk, sizes = table.column("chunk").to_numpy(), table.column("n_shingles").to_numpy()
    column = table.column("shingles").combine_chunks()
    _, place = np.unique(column.flatten().to_numpy(), return_inverse=True)
    ends = column.offsets.to_numpy()
    ends = ends - ends[0]
    cross = bool((chunk != chunk[0]).any())
    root = {c: c for c in component}

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    mark = np.zeros(int(place.max()) + 1, bool)
    for i in range(len(nodes) - int(often.max())):
        if i + 1 == len(nodes):
            break
        own = place[ends[i] : ends[i + 1]]
        mark[own] = True
        later = place[ends[i + 1] :]
        common = np.add.reduceat(mark[later], ends[i + 1 : -1] - ends[i + 1], dtype=np.int64)
        mark[own] = False
        like = 100 * common >= percent * (sizes[i] + sizes[i + 1 :] - common)
        if cross:
            like &= chunk[i + 1 :] != chunk[i]
        for j in np.flatnonzero(like) + i + 1:
            a, b = find(component[i]), find(component[j])
            if a != b:
                root[a] = b
                src.append(int(nodes[i]))
                dst.append(int(nodes[j]))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, words: int = 5, percent: int = 80) -> DataFrame:
    """One document of each group of near-duplicates, with all columns of ``docs``.

    The smallest id stays; null comes after all ids, and of rows that share an id
    one stays. Where ids are null or repeat, rows are written with a number of their
    own, by which they are told apart.
    """
    name, row = fresh(docs, "near_gone", "near_row")
    ids = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    if ids.filter("n > 1 or doc_id is null").isEmpty():
        found = near_duplicates(spark, docs, words, percent)
        gone = written_table(spark, found.filter(~F.col("kept")).select(F.col("doc_id").alias(name)), "minhash-gone")
        gone = broadcast_if_few(gone, BROADCAST_KEYS)
        return docs.join(gone, docs["doc_id"] == gone[name], "left_anti")
    keyed = written_table(spark, docs.withColumn(row, F.monotonically_increasing_id()), "minhash-keyed")
    found = _components(spark, keyed.select(F.col(row).alias("doc_id"), "text"), words, percent)
    found = found.select(F.col("doc_id").alias(name), "component_id").join(keyed.select(F.col(row).alias(name), "doc_id"), name)
    first = found.groupBy("component_id").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", name)).alias("first"))
    first = written_table(spark, first.select(F.col("first")[name].alias(name)), "minhash-first")
    return keyed.join(first, keyed[row] == first[name], "left_semi").select(*docs.columns)


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark, spark.read.parquet(f"{sf_dir}/documents.parquet"), words=4, percent=80)


ORACLE = """
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
                                                '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w
  FROM documents),
d AS MATERIALIZED (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
                               ELSE list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) END) AS g
  FROM w),
n AS MATERIALIZED (SELECT doc_id, len(g) AS n FROM d),
s AS MATERIALIZED (SELECT doc_id, unnest(g) AS x FROM d),
l AS MATERIALIZED (
  SELECT p.a, p.b FROM (
    SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c
    FROM s a JOIN s b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL) p
  JOIN n i ON i.doc_id = p.a JOIN n j ON j.doc_id = p.b
  WHERE 100 * c >= 80 * (i.n + j.n - c)),
e AS MATERIALIZED (SELECT a AS src, b AS dst FROM l UNION ALL SELECT b, a FROM l),
r(id, c) USING KEY (id) AS (
  SELECT doc_id, doc_id FROM n
  UNION
  SELECT e.dst, min(r.c) FROM r JOIN e ON e.src = r.id JOIN recurring.r q ON q.id = e.dst
  GROUP BY e.dst HAVING min(r.c) < any_value(q.c))
SELECT doc_id, n AS n_shingles, c AS component_id, doc_id = c AS kept FROM n JOIN r ON id = doc_id
"""
