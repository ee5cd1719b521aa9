"""Toxicity by two Kneser-Ney models of words, one of toxic and one of ordinary texts.

Both classes have a model of the same three levels, each with its own counts:

* A word after the word before it. Pairs are counted as Kneser and Ney do, by the
  number of different words before the pair, so passages that documents copy from
  each other do not make a pair frequent. Three of these contexts are discounted:
  pairs with fewer leave all they have to the level below.
* A word by itself, spelled as a path of nodes: its first 3 to 8 letters and then the
  whole word. Counts are of documents that hold the word; every step has the
  discounted share of its node's count.
* What the discount of a step frees goes to a backoff that both classes share: the
  number of class-and-child types seen under the parent, where all documents
  together, labelled or not, count as a third class. A form that neither class has
  seen so falls back on its stem, and on nothing where the stem is new.

Of each text the toxic and the ordinary log-likelihood are compared, normalised by
length, twice: over the whole text, and over the passage of at least ``PASSAGE`` words
where the toxic one is furthest ahead. A logistic function of both ratios (two slopes
and an offset, fitted on labelled rows that the counts have not seen) is the score.
With passages of one word and more, the highest mean is that of one step, as no mean
exceeds its largest term; two words and more dilute single words (recall 0.79 against
0.89 on the held-out rows of the tables of 10,000 documents, by passages alone).

Labels are learned only from rows whose crc32(doc_id as text) mod 5 is not 0: 1, 2
and 3 give counts, all of them, and 4 the logistic function. Label, language, source
and id are never inputs of a score. ``SAMPLE_ROWS`` bounds the rows that slopes and
offset are fitted on (rows by hash of their id; whole texts). The model is a table
of (key, toxic, ordinary) with a row per node, context and pair that a counted row
has. Up to ``BROADCAST_ENTRIES`` rows it is broadcast. Beyond that it stays in the
shared folder, in order of its keys: a task gathers texts until their different
tokens are many (``HELD_TOKENS``), and passes once over the files for the rows that
these texts need, a bounded number of rows at a time. So no text or key is
exchanged; a task reads the model as often as it has such gatherings, which at
very large inputs is what grows fastest. Every document is scored whole. Texts are
taken apart and lower-cased by the same code for counts and scores.

Defined results: null and empty texts, and texts without letters, get the score of
no evidence; an id with several labels counts as toxic when any says so; without
labels of both classes every score is 0; an empty table gives an empty result;
repeated rows get equal scores; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.llm.hashing import long_hash, string_hash
from subgraph_engine.storage import broadcast_if_few, qualified, release, text_batches, written_table

SAMPLE_ROWS = 20_000
#: Rows of the model that are broadcast, 16 bytes each, at most.
BROADCAST_ENTRIES = 4_000_000
#: Ids and labels that are broadcast at most.
BROADCAST_LABELS = 500_000
STEMS = (3, 4, 5, 6, 7, 8)
DISCOUNT = 0.75
#: Different words before a pair that are left to the level below.
PAIR_DISCOUNT = 3
#: Pairs are of words that so many counted documents hold: of all.
PAIR_DOCUMENTS = 1
PASSAGE = 1
RIDGE = 1e-2
CACHE_TOKENS = 1 << 19
#: Different tokens of the texts that a task holds for one pass over a model in files.
HELD_TOKENS = 1 << 18
#: Bytes of texts that are taken apart at once, which takes some twelve times as much.
SLICE_BYTES = 4 << 20
#: Rows of a model in files that a task has at once.
FILE_ROWS = 1 << 20
#: Words that are scored at once, in whole texts: bounds what numpy holds on the way.
SCORED_WORDS = 1 << 18
#: Pairs that a task holds before it sends the different ones.
PAIR_ROWS = 1 << 20
WORD = re.compile(r"[^\W\d_]+")
#: Kinds of the model's rows.
NODES, CONTEXTS, PAIR = 0, 1, 2
#: What a parent's row has as its key, beside the key of the node itself.
FREED = 0x5BD1E995_9E3779B9


def fold() -> Column:
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5))


def known_labels(labels: DataFrame) -> DataFrame:
    """doc_id, toxic (0 or 1) and fold of every labelled id outside the held-out fold."""
    known = labels.filter("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max((F.col("toxic") > 0).cast("int")).alias("toxic"))
    return known.withColumn("fold", fold()).filter("fold <> 0")


def sampled(known: DataFrame, rows: int = SAMPLE_ROWS) -> DataFrame:
    """At most about so many of the ids, by hash."""
    total = known.count()
    share = 1_000_000 if total <= rows else 1_000_000 * rows // total
    return known.filter(F.pmod(F.xxhash64(F.lit("sample"), "doc_id"), F.lit(1_000_000)) < share)


def tokens_of(texts: pa.Array | list[str | None]) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """Where each text's tokens end, the tokens as places among the different ones, and these."""
    texts = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string())
    lists = pc.utf8_split_whitespace(pc.utf8_lower(pc.fill_null(texts, "")))
    ends = lists.offsets.to_numpy()[1:].astype(np.int64) - lists.offsets[0].as_py()
    flat = pc.ascii_rtrim(lists.flatten(), ".,;:!?|)").dictionary_encode()
    return ends, flat.indices.to_numpy(), flat.dictionary


def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All rows, in batches of about ``SLICE_BYTES`` at most."""
    for batch in batches:
        rows = max(1, batch.num_rows // (batch.nbytes // SLICE_BYTES + 1))
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


class Numbers:
    """Numbers by key; the keys are hashes of 64 bits."""

    def __init__(self) -> None:
        self.keys, self.numbers = np.empty(0, np.int64), np.empty(0, np.int64)

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Each key's number, and whether it has one."""
        if not len(self.keys):
            return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return self.numbers[at], self.keys[at] == keys

    def add(self, keys: np.ndarray, numbers: np.ndarray) -> None:
        """New keys, none of them twice."""
        keys, numbers = np.concatenate([self.keys, keys]), np.concatenate([self.numbers, numbers])
        order = np.argsort(keys)
        self.keys, self.numbers = keys[order], numbers[order]


class Lexicon:
    """Numbers the words of texts; tokens between white space are taken apart once and kept, up to a bound."""

    def __init__(self) -> None:
        self.clear()

    def clear(self) -> None:
        #: the number of a token's word, or, below zero, the place of its words: from an end to the next among ``several``
        self.tokens = Numbers()
        self.several, self.ends = np.empty(0, np.int64), np.zeros(1, np.int64)
        self._numbers = Numbers()
        #: the keys of all words by their numbers, and the words themselves, in parts
        self.keys = np.empty(0, np.int64)
        self._parts: list[pa.Array] = []

    def __len__(self) -> int:
        return len(self.keys)

    def words(self, begin: int = 0) -> pa.Array:
        """The words from a number on."""
        left, parts = len(self) - begin, []
        for part in reversed(self._parts):
            if left <= 0:
                break
            parts.append(part.slice(max(0, len(part) - left)))
            left -= len(part)
        return pa.concat_arrays([pa.array([], pa.string()), *reversed(parts)])

    def full(self) -> bool:
        return len(self.tokens.keys) > CACHE_TOKENS

    def _number(self, words: pa.Array) -> np.ndarray:
        """The number of each word; new ones get the next."""
        keys = string_hash(words)
        at, known = self._numbers.find(keys)
        if not known.all():
            fresh, first, place = np.unique(keys[~known], return_index=True, return_inverse=True)
            at[~known] = len(self) + place
            self._numbers.add(fresh, len(self) + np.arange(len(fresh)))
            self.keys = np.concatenate([self.keys, fresh])
            self._parts.append(words.take(pa.array(np.flatnonzero(~known)[first])))
        return at

    def _take(self, tokens: pa.Array, keys: np.ndarray) -> np.ndarray:
        """What new tokens have in ``tokens``; those beyond plain letters are taken apart one by one."""
        plain = pc.and_(pc.string_is_ascii(tokens), pc.utf8_is_alpha(tokens)).to_numpy(zero_copy_only=False)
        out = np.empty(len(keys), np.int64)
        other = np.flatnonzero(~plain)
        words = list(map(WORD.findall, tokens.take(pa.array(other)).to_pylist()))
        numbers = self._number(pa.concat_arrays([tokens.filter(pa.array(plain)), pa.array(chain.from_iterable(words), pa.string())]))
        out[plain], numbers = np.split(numbers, [len(keys) - len(other)])
        out[other] = -len(self.ends) - np.arange(len(other))
        self.ends = np.concatenate([self.ends, len(self.several) + np.cumsum(list(map(len, words)), dtype=np.int64)])
        self.several = np.concatenate([self.several, numbers])
        self.tokens.add(keys, out)
        return out

    def read(self, texts: pa.Array | list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of all words in order, and where each text's words end."""
        upto, codes, tokens = tokens_of(texts)
        keys = string_hash(tokens)
        at, known = self.tokens.find(keys)
        if not known.all():
            at[~known] = self._take(tokens.filter(pa.array(~known)), keys[~known])
        at = at[codes]
        other = np.flatnonzero(at < 0)
        if not len(other):
            return at, upto
        begin = self.ends[-at[other] - 1]
        some = self.ends[-at[other]] - begin
        sizes = np.ones(len(at), np.int64)
        sizes[other] = some
        ends = np.concatenate([[0], np.cumsum(sizes)])
        numbers = np.repeat(at, sizes)
        numbers[numbers < 0] = self.several[np.repeat(begin - np.cumsum(some) + some, some) + np.arange(some.sum())]
        return numbers, ends[upto]


def word_keys(words: pa.Array | list[str]) -> np.ndarray:
    """As Spark's xxhash64 of a string has them."""
    return string_hash(words if isinstance(words, pa.Array) else pa.array(words, pa.string()))


def node_keys(names: pa.Array, end: str = "") -> np.ndarray:
    """Keys of the nodes of these names."""
    return string_hash(pc.binary_join_element_wise("n", names, end, ""))


def different(numbers: np.ndarray) -> np.ndarray:
    """The different ones, in order; np.unique takes several times as long on millions of numbers that hardly repeat."""
    numbers = np.sort(numbers)
    return numbers[np.concatenate([[True], numbers[1:] != numbers[:-1]])] if len(numbers) else numbers


# counts

COUNTED = "w string, n0 long, n1 long, c0 long, c1 long"


def _count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Words, with the documents (n) that hold them and their places (c) by class; a class of null adds neither."""
    lexicon = Lexicon()
    sums = np.zeros((4, 0), np.int64)

    def flush() -> Iterator[pa.RecordBatch]:
        words = lexicon.words()
        for at in range(0, len(words), 50_000):
            part = slice(at, at + 50_000)
            yield pa.RecordBatch.from_arrays([words.slice(at, 50_000), *(pa.array(s[part]) for s in sums)], ["w", "n0", "n1", "c0", "c1"])

    for batch in slices(batches):
        counted = pc.is_valid(batch.column("toxic"))
        # of other documents it only matters which words there are
        lexicon.read(batch.column("text").filter(pc.invert(counted)))
        numbers, ends = lexicon.read(batch.column("text").filter(counted))
        n = len(lexicon)
        sums = np.pad(sums, ((0, 0), (0, n - sums.shape[1])))
        kind = batch.column("toxic").filter(counted).to_numpy()
        own = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))
        once = different(own << 32 | numbers)
        for c in (0, 1):
            sums[c] += np.bincount(once[kind[once >> 32] == c] & 0xFFFFFFFF, minlength=n)
            sums[2 + c] += np.bincount(numbers[kind[own] == c], minlength=n)
        if lexicon.full():
            yield from flush()
            lexicon.clear()
            sums = np.zeros((4, 0), np.int64)
    yield from flush()


def nodes_of(w: str) -> Column:
    """The nodes of a word's path."""
    stems = [F.when(F.length(w) > k, F.substring(w, 1, k)) for k in STEMS]
    return F.array_compact(F.array(*stems, F.concat(w, F.lit("$"))))


def parent_of(node: str) -> Column:
    """The node before: one letter less, eight letters at most, none below three."""
    bare = F.rtrim(F.col(node), F.lit("$"))
    size = F.least(F.length(bare) - 1, F.lit(STEMS[-1]))
    return F.when(size >= STEMS[0], F.substring(bare, F.lit(1), size)).otherwise(F.lit(""))


def word_counts(docs: DataFrame, known: DataFrame) -> DataFrame:
    """w, n0, n1, c0, c1 of all documents' words; what ``known`` has counts for its class."""
    counted = known.filter("fold <> 4").select("doc_id", "toxic")
    rows = docs.select("doc_id", "text").join(broadcast_if_few(counted, BROADCAST_LABELS), "doc_id", "left").select("text", "toxic")
    sums = [F.sum(c).alias(c) for c in ("n0", "n1", "c0", "c1")]
    return rows.mapInArrow(_count_words, COUNTED).groupBy("w").agg(*sums)


def node_entries(words: DataFrame) -> DataFrame:
    """kind, key, x, y: log-likelihoods of steps to nodes, toxic and ordinary, and what is freed at their parents for unseen children."""
    steps = words.select(F.explode(nodes_of("w")).alias("node"), "n0", "n1")
    nodes = steps.groupBy("node").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")).withColumn("parent", parent_of("node"))
    types = lambda n: F.count_if(F.col(n) > 0)
    parents = nodes.groupBy("parent").agg(
        F.sum("n0").alias("m0"), F.sum("n1").alias("m1"), types("n0").alias("t0"), types("n1").alias("t1"), F.count(F.lit(1)).alias("t")
    )
    parents = parents.filter("m0 + m1 > 0")
    seen = nodes.filter("n0 + n1 > 0").join(parents, "parent")
    pooled = ((F.col("n0") > 0).cast("int") + (F.col("n1") > 0).cast("int") + 1.5) / (F.col("t0") + F.col("t1") + F.col("t") + 1.0)

    def step(n: str, m: str, t: str) -> Column:
        own = F.greatest(F.col(n) - F.lit(DISCOUNT), F.lit(0.0)) + DISCOUNT * F.col(t) * pooled
        return F.log(F.when(F.col(m) > 0, own / F.col(m)).otherwise(pooled))

    freed = lambda m, t: F.log(F.when(F.col(m) > 0, DISCOUNT * F.col(t) / F.col(m)).otherwise(F.lit(1.0)))
    key = lambda c: F.xxhash64(F.concat(F.lit("n"), c))
    kind = F.lit(NODES).alias("kind")
    known = seen.select(kind, key(F.col("node")).alias("key"), step("n1", "m1", "t1").alias("x"), step("n0", "m0", "t0").alias("y"))
    return known.unionByName(parents.select(kind, key(F.col("parent")).bitwiseXOR(F.lit(FREED)).alias("key"), freed("m1", "t1").alias("x"), freed("m0", "t0").alias("y")))


PAIRS = "toxic int, h long, w long, g int"


def _pairs_of(frequent: np.ndarray | None):
    """Different (class, word, next word, word before both) of batches; of frequent words alone where these are given."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon()
        held: list[np.ndarray] = []

        def flush() -> Iterator[pa.RecordBatch]:
            rows = np.concatenate(held, axis=1) if held else np.empty((4, 0), np.int64)
            mixed = long_hash(long_hash(rows[1]) ^ rows[2]) ^ (rows[3] << 1 | rows[0])
            rows = rows[:, np.unique(mixed, return_index=True)[1]]
            for at in range(0, rows.shape[1], 100_000):
                part = rows[:, at : at + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(part[0], pa.int32()), pa.array(part[1]), pa.array(part[2]), pa.array(part[3], pa.int32())], ["toxic", "h", "w", "g"])
            held.clear()

        for batch in slices(batches):
            numbers, ends = lexicon.read(batch.column("text"))
            keys = lexicon.keys
            usable = np.ones(len(keys), bool)
            if frequent is not None:
                at = np.minimum(np.searchsorted(frequent, keys), max(len(frequent) - 1, 0))
                usable = frequent[at] == keys if len(frequent) else ~usable
            toxic = np.array(batch.column("toxic").to_pylist(), np.int64)
            own = np.repeat(np.arange(len(ends)), np.diff(ends, prepend=0))
            good = usable[numbers]
            second = np.flatnonzero(good[1:] & good[:-1] & (own[1:] == own[:-1])) + 1
            first = second - 1
            before = np.where((first > 0) & (own[first - 1] == own[first]), keys[numbers[first - 1]], 0)
            held.append(np.stack([toxic[own[second]], keys[numbers[first]], keys[numbers[second]], before.astype(np.int32).astype(np.int64)]))
            if sum(x.shape[1] for x in held) >= PAIR_ROWS:
                yield from flush()
            if lexicon.full():
                lexicon.clear()
        yield from flush()

    return run


def pair_entries(spark: SparkSession, docs: DataFrame, known: DataFrame, words: DataFrame) -> DataFrame:
    """kind, key, x, y: shares of pairs above the discount, and logarithms of what their first words leave to the level below.

    A pair has at most as many contexts in a class as each of its words has places
    there, so words with too few places for the discount need not be exchanged.
    """
    frequent = words.filter(f"n0 + n1 >= {PAIR_DOCUMENTS} and greatest(c0, c1) > {PAIR_DISCOUNT}").select(F.xxhash64("w").alias("key"), "c0", "c1")
    frequent = written_table(spark, frequent, "toxic-frequent")
    few = frequent.count() <= BROADCAST_ENTRIES
    keys = np.sort(frequent.select("key").toArrow().column(0).to_numpy()) if few else None  # bounded by the count
    rows = docs.select("doc_id", "text").join(broadcast_if_few(known.filter("fold <> 4"), BROADCAST_LABELS), "doc_id").select("text", "toxic")
    pairs = rows.mapInArrow(_pairs_of(keys), PAIRS)
    if not few:
        for end in ("h", "w"):
            pairs = pairs.join(frequent.select(F.col("key").alias(end)), end, "left_semi")
    # one exchange serves both groupings
    pairs = pairs.repartition("h", "w").groupBy("h", "w", "toxic", "g").agg(F.lit(1).alias("one"))
    pairs = pairs.groupBy("h", "w").agg(F.sum("toxic").alias("k1"), F.sum(1 - F.col("toxic")).alias("k0"))
    kept = pairs.filter(f"greatest(k0, k1) > {PAIR_DISCOUNT}")
    above = lambda k: F.greatest(F.col(k) - PAIR_DISCOUNT, F.lit(0))
    kept = kept.select("h", "w", above("k1").alias("a1"), above("k0").alias("a0")).join(frequent.withColumnRenamed("key", "h"), "h")
    share = lambda c: F.when(F.col(f"c{c}") > 0, F.col(f"a{c}") / F.col(f"c{c}")).otherwise(F.lit(0.0))
    kept = written_table(spark, kept.select("h", "w", share(1).alias("f1"), share(0).alias("f0")), "toxic-pairs")
    left = lambda c: F.log(F.greatest(1 - F.sum(f"f{c}"), F.lit(1e-9)))
    contexts = kept.groupBy("h").agg(left(1).alias("x"), left(0).alias("y"))
    release(spark, frequent)
    contexts = contexts.select(F.lit(CONTEXTS).alias("kind"), F.xxhash64("h").alias("key"), "x", "y")
    pair_key = F.xxhash64("h").bitwiseXOR(F.col("w")).alias("key")
    return contexts.unionByName(kept.select(F.lit(PAIR).alias("kind"), pair_key, F.col("f1").alias("x"), F.col("f0").alias("y")))


# scores


class Entries:
    """Pairs of numbers by key."""

    def __init__(self, keys: np.ndarray | None = None, x: np.ndarray | None = None, y: np.ndarray | None = None):
        none = np.empty(0, np.float32)
        self.keys = np.empty(0, np.int64) if keys is None else keys
        self.x, self.y = (none, none) if x is None else (x, y)

    @classmethod
    def sorted(cls, keys: np.ndarray, x: np.ndarray, y: np.ndarray) -> Entries:
        order = np.argsort(keys, kind="stable")
        return cls(keys[order], x[order], y[order])

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Both numbers of each key, 0 where there is none, and whether there is one."""
        if not len(self.keys):
            return np.zeros(len(keys)), np.zeros(len(keys)), np.zeros(len(keys), bool)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        hit = self.keys[at] == keys
        return np.where(hit, self.x[at], 0.0), np.where(hit, self.y[at], 0.0), hit

    def __eq__(self, other: object) -> bool:
        return isinstance(other, Entries) and np.array_equal(self.keys, other.keys) and np.allclose(self.x, other.x) and np.allclose(self.y, other.y)


Model = tuple[Entries, Entries, Entries]


def model_of(kinds: np.ndarray, keys: np.ndarray, x: np.ndarray, y: np.ndarray) -> Model:
    return tuple(Entries.sorted(keys[kinds == k], x[kinds == k], y[kinds == k]) for k in (NODES, CONTEXTS, PAIR))


def collected(rows: DataFrame) -> Model:
    """At most BROADCAST_ENTRIES rows: bounded whatever the input."""
    table = rows.select("kind", "key", F.col("x").cast("float"), F.col("y").cast("float")).toArrow()
    return model_of(*(table.column(k).to_numpy() for k in range(4)))


def word_likelihoods(words: pa.Array, nodes: Entries) -> np.ndarray:
    """Toxic and ordinary log-likelihood of each word's path, level by level; a path ends at its first unseen node."""
    out = np.zeros((2, len(words)))
    alive, parents = np.arange(len(words)), np.repeat(word_keys(["n"]), len(words))
    for k in (*STEMS, None):
        ending = np.ones(len(alive), bool) if k is None else pc.utf8_length(words).to_numpy() <= k
        keys = np.empty(len(alive), np.int64)
        keys[ending] = node_keys(words.filter(pa.array(ending)), "$")
        if k is not None:
            keys[~ending] = node_keys(pc.utf8_slice_codeunits(words.filter(pa.array(~ending)), 0, k))
        x, y, hit = nodes.find(keys)
        out[0][alive] += x
        out[1][alive] += y
        x, y, _ = nodes.find(parents[~hit] ^ FREED)
        out[0][alive[~hit]] += x
        out[1][alive[~hit]] += y
        on = hit & ~ending
        alive, parents, words = alive[on], keys[on], words.filter(pa.array(on))
        if not len(alive):
            break
    return out


def model_in_files(folder: str, wanted: np.ndarray) -> Model:
    """The rows with the wanted keys (different ones, in order); every row is read, a bounded number at a time."""
    files, path = pafs.FileSystem.from_uri(folder)
    found: list[list[np.ndarray]] = [[np.empty(0, t)] for t in (np.int8, np.int64, np.float32, np.float32)]
    for file in sorted(f.path for f in files.get_file_info(pafs.FileSelector(path)) if f.path.endswith(".parquet")):
        with files.open_input_file(file) as source:
            for batch in pq.ParquetFile(source).iter_batches(FILE_ROWS, columns=["kind", "key", "x", "y"]):
                columns = [batch.column(c).to_numpy() for c in ("kind", "key", "x", "y")]
                keys = columns[1]
                if not len(keys):
                    continue
                part = wanted[np.searchsorted(wanted, keys[0]) : np.searchsorted(wanted, keys[-1], "right")]
                first, end = np.searchsorted(keys, part), np.searchsorted(keys, part, "right")
                # rows of different kinds may have one key
                for more in range(int((end - first).max(initial=0))):
                    rows = (first + more)[end - first > more]
                    for out, column in zip(found, columns):
                        out.append(column[rows])
    return model_of(*map(np.concatenate, found))


def chances(weights: list[float], measures: np.ndarray) -> np.ndarray:
    """Scores from the texts' measures, a column each."""
    *slopes, offset = weights
    return 1.0 / (1.0 + np.exp(-np.clip(np.dot(slopes, measures) + offset, -40.0, 40.0)))


class Scorer:
    """Scores texts with a model; keeps a bounded number of words.

    A model too large for a broadcast is in ``table``, in order of its keys, instead of ``model``.
    """

    def __init__(self, model: Model | None = None, weights: list[float] | None = None, table: DataFrame | None = None):
        self.model, self.weights, self.table = model or (Entries(), Entries(), Entries()), weights, table
        self.lexicon = Lexicon()
        self._forget()

    def _forget(self) -> None:
        self.lexicon.clear()
        #: of each word: toxic and ordinary log-likelihood, and what it leaves to the level below as a context
        self.values = np.empty((4, 0))
        self.mixed = np.empty(0, np.int64)

    def _learn(self) -> None:
        begin = len(self.mixed)
        if begin == len(self.lexicon):
            return
        nodes, contexts, _ = self.model
        mixed = long_hash(self.lexicon.keys[begin:])
        new = np.concatenate([word_likelihoods(self.lexicon.words(begin), nodes), np.stack(contexts.find(mixed)[:2])])
        self.values = np.concatenate([self.values, new], axis=1)
        self.mixed = np.concatenate([self.mixed, mixed])

    def measures(self, texts: list[str | None]) -> np.ndarray:
        """The length-normalised log-likelihood ratios of each text's most toxic passage and of the whole text."""
        if self.lexicon.full():
            self._forget()
        read = self.lexicon.read(texts)
        self._learn()
        return self._measures(*read)

    def ratios(self, texts: list[str | None]) -> np.ndarray:
        """The first of the measures: that of the most toxic passage."""
        return self.measures(texts)[0]

    def _measures(self, numbers: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """The measures of texts from their words' numbers, some whole texts at a time."""
        out, at, begin = np.zeros((2, len(ends))), 0, 0
        while at < len(ends):
            upto = max(at + 1, int(np.searchsorted(ends, begin + SCORED_WORDS, "right")))
            step = self._steps(numbers[begin : ends[upto - 1]], ends[at:upto] - begin)
            out[0, at:upto] = self._highest_of(step, ends[at:upto] - begin)
            out[1, at:upto] = self._whole_of(step, ends[at:upto] - begin)
            at, begin = upto, ends[upto - 1]
        return out

    def _steps(self, numbers: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """The log-likelihood ratio of every word of the texts."""
        if not len(numbers):
            return np.zeros(0)
        starts = np.concatenate([[0], ends[:-1]])
        step = (self.values[0] - self.values[1])[numbers]
        # a word after the one before it in its text, where that leaves less than all to the level below
        leaves = (self.values[2] != 0) | (self.values[3] != 0)
        second = np.flatnonzero(leaves[numbers[:-1]]) + 1
        second = second[~np.isin(second, starts)]
        first, own = numbers[second - 1], numbers[second]
        left1, left0 = self.values[2][first], self.values[3][first]
        step[second] += left1 - left0
        f1, f0, hit = self.model[2].find(self.mixed[first] ^ self.lexicon.keys[own])
        if hit.any():
            x, y = self.values[0][own[hit]], self.values[1][own[hit]]
            step[second[hit]] = np.log(f1[hit] + np.exp(x + left1[hit])) - np.log(f0[hit] + np.exp(y + left0[hit]))
        return step

    @staticmethod
    def _highest_of(step: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """The highest mean of each text's passages of at least ``PASSAGE`` words (of all its words, if these are fewer)."""
        out, starts = np.zeros(len(ends)), np.concatenate([[0], ends[:-1]])
        if PASSAGE == 1:
            full = np.flatnonzero(starts < ends)
            out[full] = np.maximum.reduceat(step, starts[full]) if len(full) else 0.0
            return out
        upto = np.concatenate([[0.0], np.cumsum(step)])
        for i, (a, b) in enumerate(zip(starts.tolist(), ends.tolist())):
            # of a passage twice as long, one half has no lower mean
            if least := min(PASSAGE, b - a):
                out[i] = max((upto[a + n : b + 1] - upto[a : b + 1 - n]).max() / n for n in range(least, min(2 * least, b - a + 1)))
        return out

    @staticmethod
    def _whole_of(step: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """The mean of all of each text's words."""
        out, starts = np.zeros(len(ends)), np.concatenate([[0], ends[:-1]])
        full = np.flatnonzero(starts < ends)
        out[full] = np.add.reduceat(step, starts[full]) / (ends - starts)[full] if len(full) else 0.0
        return out

    def _needed(self, read: list[tuple[np.ndarray, np.ndarray]]) -> np.ndarray:
        """Keys of all entries that the texts read so may need, whatever their kind, in order."""
        words, keys = self.lexicon.words(), self.lexicon.keys
        mixed = long_hash(keys)
        wanted = [mixed, node_keys(words, "$")]
        sizes = pc.utf8_length(words).to_numpy()
        for k in (0, *STEMS):
            stems = different(node_keys(pc.utf8_slice_codeunits(words.filter(pa.array(sizes > k)), 0, k)))
            wanted += [stems, stems ^ FREED]
        for numbers, _ in read:
            pairs = different(numbers[:-1] << 32 | numbers[1:])
            wanted.append(mixed[pairs >> 32] ^ keys[pairs & 0xFFFFFFFF])
        return different(np.concatenate(wanted))

    def ratios_by_files(self, batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
        """Each batch with its texts' ratios, by a model in files."""
        return ((batch, found[0]) for batch, found in self.measures_by_files(batches, folder))

    def measures_by_files(self, batches: Iterator[pa.RecordBatch], folder: str) -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
        """Each batch with its texts' measures, by a model in files."""
        held: list[tuple[pa.RecordBatch, tuple[np.ndarray, np.ndarray]]] = []

        def flush() -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
            self.model = model_in_files(folder, self._needed([read for _, read in held]))
            self._learn()
            for batch, read in held:
                yield batch, self._measures(*read)
            held.clear()
            self._forget()

        for batch in slices(batches):
            held.append((batch, self.lexicon.read(batch.column("text"))))
            if len(self.lexicon.tokens.keys) > HELD_TOKENS or sum(len(read[0]) for _, read in held) > CACHE_TOKENS << 3:
                yield from flush()
        if held:
            yield from flush()

    def scores(self, texts: list[str | None]) -> np.ndarray:
        return chances(self.weights, self.measures(texts)) if self.weights else np.zeros(len(texts))

    def score(self, text: str | None) -> float:
        return float(self.scores([text])[0])


def fit_logistic(x: np.ndarray, y: np.ndarray) -> list[float]:
    """Ridge logistic regression by Newton's method; the intercept comes last."""
    a = np.c_[x, np.ones(len(x))]
    w = np.zeros(a.shape[1])
    ridge = RIDGE * np.eye(a.shape[1])
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -40, 40)))
        w += np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + ridge, a.T @ (y - p) - ridge @ w)
    return w.tolist()


def in_order(spark: SparkSession, entries: DataFrame) -> DataFrame:
    """The model's rows in order of their keys, file by file, written for tasks that pass over them."""
    rows = entries.select(F.col("kind").cast("byte").alias("kind"), "key", F.col("x").cast("float").alias("x"), F.col("y").cast("float").alias("y"))
    return written_table(spark, rows.repartitionByRange("key").sortWithinPartitions("key"), "toxic-model")


def model_entries(spark: SparkSession, docs: DataFrame, known: DataFrame) -> DataFrame:
    """kind, key, x, y of the whole model, written."""
    words = written_table(spark, word_counts(docs, known), "toxic-words")
    nodes = written_table(spark, node_entries(words), "toxic-nodes")
    entries = written_table(spark, nodes.unionByName(pair_entries(spark, docs, known, words)), "toxic-entries")
    release(spark, words, nodes)
    return entries


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, rows: int = SAMPLE_ROWS) -> Scorer:
    text_batches(spark)
    known = written_table(spark, known_labels(labels), "toxic-labels")
    held = docs.select("doc_id").join(broadcast_if_few(known, BROADCAST_LABELS), "doc_id")
    counts = {r["toxic"]: r["n"] for r in held.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not (counts.get(0) and counts.get(1)):
        return Scorer()
    entries = model_entries(spark, docs, known)
    if entries.count() <= BROADCAST_ENTRIES:
        model = Scorer(collected(entries))
    else:
        model = Scorer(table=in_order(spark, entries))
    release(spark, entries)
    chosen = sampled(known.filter("fold = 4"), rows)
    sample = docs.select("doc_id", "text").join(broadcast_if_few(chosen, BROADCAST_LABELS), "doc_id").select("text", "toxic")
    measures = scoring(spark, model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, (highest, whole) in measures(batches):
            yield pa.RecordBatch.from_arrays([pa.array(highest, pa.float64()), pa.array(whole, pa.float64()), batch.column("toxic")], ["highest", "whole", "toxic"])

    # about SAMPLE_ROWS rows of three numbers at most
    seen = sample.mapInArrow(run, "highest double, whole double, toxic int").toArrow()
    release(spark, known)
    model.weights = fit_logistic(np.c_[seen.column("highest").to_numpy(), seen.column("whole").to_numpy()], seen.column("toxic").to_numpy().astype(float))
    return model


def scoring(spark: SparkSession, model: Scorer) -> Callable[[Iterator[pa.RecordBatch]], Iterator[tuple[pa.RecordBatch, np.ndarray]]]:
    """What gives each batch with its texts' measures."""
    if model.table is not None:
        folder = qualified(spark, model.table._shared_path)
        return lambda batches: Scorer().measures_by_files(batches, folder)
    shared = spark.sparkContext.broadcast(model.model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray]]:
        own = Scorer(shared.value)
        for batch in slices(batches):
            yield batch, own.measures(batch.column("text"))

    return run


def score(spark: SparkSession, docs: DataFrame, scorer: Scorer) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of ``docs``."""
    text_batches(spark)
    rows, measures, weights = docs.select(F.col("doc_id").cast("long"), "text"), scoring(spark, scorer), scorer.weights

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, found in measures(batches):
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(chances(weights, found), pa.float64())], ["doc_id", "score"])

    scored = rows.mapInArrow(run, "doc_id long, score double") if weights else rows.select("doc_id", F.lit(0.0).alias("score"))
    return scored.select(
        "doc_id", F.coalesce(fold() == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted")
    )


def drop_toxic(spark: SparkSession, docs: DataFrame, scorer: Scorer) -> DataFrame:
    """The rows of ``docs`` that are not predicted toxic, all columns as they were."""
    text_batches(spark)
    measures, weights = scoring(spark, scorer), scorer.weights
    if not weights:
        return docs

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, found in measures(batches):
            yield batch.filter(pa.array(chances(weights, found) < 0.5, pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def scores_of_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return score(spark, docs, fit(spark, docs, labels))
