"""Token ids in files of bit- or byte-planes.

A file holds the ids of consecutive documents in chunks of a fixed number of ids.
A chunk's 32-bit ids are transposed into planes, the i-th plane holding the i-th
bit (or byte) of every id, and each plane is compressed by itself with
zstandard: high planes are almost constant, low planes are stored nearly as they
are. An index at the end gives every chunk's place, so that any run of ids is
read without the rest.

Layout (integers little-endian):

* ``PLN1`` and one byte: planes per id (32 for bits, 4 for bytes);
* the chunks, each its planes one after another;
* the index, zstandard over: number of documents, of chunks and of ids per chunk
  (three unsigned 64-bit); document ids (signed 64-bit), which of them are null (bytes)
  and lengths in ids (unsigned 64-bit); ids in each chunk (unsigned 64-bit); compressed bytes of each
  plane of each chunk (unsigned 32-bit);
* the index's place and size (two unsigned 64-bit) and ``PLN1``.

``write_files`` puts documents in ascending ``doc_id`` order over files: range
placement, a sort in each partition, and one or more files a partition. Files
are written under a name of the attempt and listed in a manifest table, so a
repeated task leaves at most a file that nothing lists. ``read_files`` takes
places from the manifest and contents from the files alone.

Defined results: null text is empty; an empty text has the end id alone; null ids
come first; rows that repeat an id stand in the order of their text; an empty
table makes an empty manifest; extra columns are ignored.
"""

from __future__ import annotations

import struct
import unicodedata
import uuid
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import regex
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from subgraph_engine.storage import qualified, shared_path, shuffle_width, text_batches, written_table

MAGIC = b"PLN1"
CHUNK_IDS = 1 << 16
FILE_IDS = 1 << 22
LEVEL = 3
WORD_CACHE = 1 << 19
CACHED_CHARS = 48
#: Fixed value: the split pattern of the public tokenizer file.
PRETOKEN = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")

FRESH = regex.compile("[\U00010000-\U0001efff\U00020000-\U0010ffff]")


def pack_chunk(ids: np.ndarray, planes: int) -> list[bytes]:
    """The compressed planes of a chunk of unsigned 32-bit ids."""
    rows = np.ascontiguousarray(ids, "<u4").view(np.uint8).reshape(-1, 4)
    if planes == 32:
        rows = np.packbits(np.unpackbits(rows, axis=1, bitorder="little").T, axis=1, bitorder="little")
    else:
        rows = rows.T
    press = zstandard.ZstdCompressor(level=LEVEL)
    return [press.compress(np.ascontiguousarray(p).tobytes()) for p in rows]


def unpack_chunk(parts: list[bytes], n: int) -> np.ndarray:
    press = zstandard.ZstdDecompressor()
    size = -(-n // 8) if len(parts) == 32 else n
    rows = np.stack([np.frombuffer(press.decompress(p, max_output_size=size or 1), np.uint8) for p in parts])
    if len(parts) == 32:
        rows = np.packbits(np.unpackbits(rows, axis=1, count=n, bitorder="little").T, axis=1, bitorder="little")
    else:
        rows = rows.T
    return np.ascontiguousarray(rows).view("<u4").reshape(-1)


class PlaneWriter:
    """Collects documents and gives the file's bytes; memory is bounded by the file's size."""

    def __init__(self, planes: int = 4, chunk_ids: int = CHUNK_IDS):
        self.planes, self.chunk_ids = planes, chunk_ids
        self.body, self.sizes, self.counts = [MAGIC + bytes([planes])], [], []
        self.docs: list[int | None] = []
        self.lengths: list[int] = []
        self.waiting: list[np.ndarray] = []
        self.n_waiting = self.n_ids = 0

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        self.docs.append(doc_id)
        self.lengths.append(len(ids))
        self.waiting.append(ids)
        self.n_waiting += len(ids)
        self.n_ids += len(ids)
        if self.n_waiting >= self.chunk_ids:
            self._chunks(whole=True)

    def _chunks(self, whole: bool) -> None:
        flat = np.concatenate(self.waiting) if self.waiting else np.empty(0, np.uint32)
        end = len(flat) // self.chunk_ids * self.chunk_ids if whole else len(flat)
        for at in range(0, end, self.chunk_ids):
            part = flat[at : min(at + self.chunk_ids, end)]
            packed = pack_chunk(part, self.planes)
            self.body += packed
            self.sizes.append([len(p) for p in packed])
            self.counts.append(len(part))
        self.waiting, self.n_waiting = [flat[end:]], len(flat) - end

    def finish(self) -> bytes:
        self._chunks(whole=False)
        index = struct.pack("<QQQ", len(self.docs), len(self.counts), self.chunk_ids)
        index += np.array([d or 0 for d in self.docs], "<i8").tobytes()
        index += bytes(d is None for d in self.docs)
        index += np.array(self.lengths, "<u8").tobytes() + np.array(self.counts, "<u8").tobytes()
        index += np.array(self.sizes, "<u4").tobytes()
        packed = zstandard.ZstdCompressor(level=LEVEL).compress(index)
        body = b"".join(self.body)
        return body + packed + struct.pack("<QQ", len(body), len(packed)) + MAGIC


class PlaneReader:
    """Reads runs of ids from a file through its index."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        at, n = struct.unpack("<QQ", source.read_at(20, size - 20)[:16])
        index = zstandard.ZstdDecompressor().decompress(source.read_at(n, at))
        n_docs, n_chunks, self.chunk_ids = struct.unpack_from("<QQQ", index)
        head = source.read_at(5, 0)
        if head[:4] != MAGIC:
            raise ValueError("not a file of planes")
        planes, pos = head[4], 24

        def column(kind: str, count: int) -> np.ndarray:
            nonlocal pos
            found = np.frombuffer(index, kind, count, pos)
            pos += found.nbytes
            return found

        ids, none = column("<i8", n_docs), column("u1", n_docs)
        self.doc_ids: list[int | None] = [None if x else int(i) for i, x in zip(ids, none)]
        self.lengths = column("<u8", n_docs)
        self.counts = column("<u8", n_chunks)
        self.sizes = column("<u4", n_chunks * planes).reshape(n_chunks, planes)
        self.starts = 5 + np.concatenate([[0], np.cumsum(self.sizes.sum(axis=1, dtype=np.int64))])

    def chunk(self, k: int) -> np.ndarray:
        data = self.source.read_at(int(self.starts[k + 1] - self.starts[k]), int(self.starts[k]))
        ends = np.concatenate([[0], np.cumsum(self.sizes[k], dtype=np.int64)])
        return unpack_chunk([data[a:b] for a, b in zip(ends, ends[1:])], int(self.counts[k]))

    def documents(self) -> Iterator[tuple[int | None, np.ndarray]]:
        """Each document and its ids, one chunk in memory at a time."""
        left, at, k = np.empty(0, np.uint32), 0, 0
        for doc, n in zip(self.doc_ids, self.lengths):
            parts, need = [], int(n)
            while need > len(left) - at:
                parts.append(left[at:])
                need -= len(left) - at
                left, at, k = self.chunk(k), 0, k + 1
            parts.append(left[at : at + need])
            at += need
            yield doc, np.concatenate(parts)


class WordEncoder:
    """A library tokenizer that ignores white space and case, with bounded caches.

    White space separates pretokens and is dropped, so a text's ids are those of
    the stretches between its spaces, tabs and line ends, one after another, and
    a stretch's ids are those of its pretokens. Stretches and pretokens are kept;
    the library encodes all new pretokens of a text in one call, whose ids fall
    apart after each token that ends a word.

    Texts with marks of special tokens, with letters whose lower case depends on
    their place, or with letters beyond the basic plane, whose class depends on
    the Unicode version, go to the library as they are.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        size = self.tokenizer.get_vocab_size(with_added_tokens=True)
        self.ends = np.zeros(size, bool)
        for token, i in self.tokenizer.get_vocab().items():
            self.ends[i] = token.endswith("</w>")
        self.stretches: dict[str, bytes] = {"": b""}
        self.pretokens: dict[str, bytes] = {}

    def _library(self, text: str) -> np.ndarray:
        return np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, "<u4")

    def encode(self, text: str, end: bytes) -> np.ndarray:
        if "<|" in text or "\u03a3" in text or "\u0130" in text or not text.isascii() and FRESH.search(text):
            return np.concatenate([self._library(text), np.frombuffer(end, "<u4")])
        text = unicodedata.normalize("NFC", text).lower()
        words = text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")
        known = self.stretches
        new = set(words).difference(known)
        if len(known) + len(new) > WORD_CACHE:
            known.clear()
            known[""] = b""
            new = set(words).difference(known)
        self._learn(new)
        ids = b"".join([*map(known.__getitem__, words), end])
        for word in new:
            if len(word) > CACHED_CHARS:
                del known[word]
        return np.frombuffer(ids, "<u4")

    def _learn(self, new: set[str]) -> None:
        parts = {word: PRETOKEN.findall(word) for word in new}
        if len(self.pretokens) > WORD_CACHE:
            self.pretokens.clear()
        known = self.pretokens
        unseen = list({p for own in parts.values() for p in own if p not in known})
        if unseen:
            ids = self._library(" ".join(unseen))
            cuts = np.flatnonzero(self.ends[ids]) + 1
            found = [ids[a:b].tobytes() for a, b in zip([0, *cuts], cuts)]
            if len(found) != len(unseen):
                found = [self._library(p).tobytes() for p in unseen]
            known.update(zip(unseen, found))
        for word, own in parts.items():
            self.stretches[word] = b"".join(map(known.__getitem__, own))


@lru_cache(maxsize=4)
def word_encoder(path: str) -> WordEncoder:
    return WordEncoder(path)


def _open(folder: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(folder)


MANIFEST = "part int, seq int, path string, n_docs long, n_ids long"


def write_files(
    spark: SparkSession, docs: DataFrame, tokenizer: str, folder: str, end_id: int, planes: int = 4, file_ids: int = FILE_IDS
) -> DataFrame:
    """Encodes and writes all documents; returns the manifest: part, seq, path, n_docs, n_ids.

    ``folder`` is a URI that all executors reach (file, hdfs, s3 or gs).
    """
    rows = docs.select(F.col("doc_id").cast("long"), "text")
    order = [F.col("doc_id").asc_nulls_first(), F.coalesce("text", F.lit(""))]
    placed = rows.repartitionByRange(shuffle_width(spark), order[0]).sortWithinPartitions(*order)
    placed = placed.select("*", F.spark_partition_id().alias("part"))
    end = np.array([end_id], "<u4").tobytes()
    text_batches(spark)
    folder = qualified(spark, folder)
    _make_folder(spark, folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = word_encoder(tokenizer)
        fs, root = _open(folder)
        writer, part, seq = PlaneWriter(planes), None, 0

        def close() -> pa.RecordBatch:
            path = f"{root}/part-{part:06d}-{seq:04d}-{uuid.uuid4().hex}.planes"
            with fs.open_output_stream(f"{path}.tmp") as f:
                f.write(writer.finish())
            fs.move(f"{path}.tmp", path)
            row = {"part": part, "seq": seq, "path": path, "n_docs": len(writer.docs), "n_ids": writer.n_ids}
            return pa.RecordBatch.from_pylist([row], _manifest_schema())

        for batch in batches:
            ids, texts = batch.column("doc_id").to_pylist(), batch.column("text").to_pylist()
            part = batch.column("part")[0].as_py() if batch.num_rows else part
            for doc_id, text in zip(ids, texts):
                writer.add(doc_id, encoder.encode(text or "", end))
                if writer.n_ids >= file_ids:
                    yield close()
                    writer, seq = PlaneWriter(planes), seq + 1
        if writer.docs:
            yield close()

    return written_table(spark, placed.mapInArrow(run, MANIFEST), "planes-manifest")


def _manifest_schema() -> pa.Schema:
    whole, text, long = pa.int32(), pa.string(), pa.int64()
    return pa.schema([("part", whole), ("seq", whole), ("path", text), ("n_docs", long), ("n_ids", long)])


def _make_folder(spark: SparkSession, folder: str) -> None:
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(folder)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).mkdirs(target)


READ = "doc_id long, start long, n_tokens long, ids_crc32 long"


def read_files(spark: SparkSession, manifest: DataFrame, folder: str) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of every document, from the files."""
    before = Window.orderBy("part", "seq").rowsBetween(Window.unboundedPreceding, -1)
    # one row for each file
    files = manifest.withColumn("first_id", F.coalesce(F.sum("n_ids").over(before), F.lit(0)))
    files = files.select("path", "first_id").repartition(shuffle_width(spark), "path")
    folder = qualified(spark, folder)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, _ = _open(folder)
        for batch in batches:
            for path, start in zip(batch.column("path").to_pylist(), batch.column("first_id").to_pylist()):
                rows = []
                with fs.open_input_file(path) as f:
                    for doc, ids in PlaneReader(f).documents():
                        rows.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                        start += len(ids)
                columns = [pa.array(list(c), pa.int64()) for c in zip(*rows)]
                yield pa.RecordBatch.from_arrays(columns, ["doc_id", "start", "n_tokens", "ids_crc32"])

    return files.mapInArrow(run, READ)


def word_bpe_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def files_of_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared_path(spark, "planes")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    manifest = write_files(spark, docs, word_bpe_path(), folder, end_id=2)
    return read_files(spark, manifest, folder)
