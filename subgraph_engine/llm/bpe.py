"""Byte-level BPE as a bounded-lookahead streaming transducer, and its decoder.

Text goes in piece by piece and ids come out as soon as no later text can change
them. Two bounds make that possible:

* Pretokens. A boundary after a run of letters or of digits, or where white
  space follows other text, is final once the next character is known.
* Merges. Inside one pretoken of any length, rules act in order of rank, and
  what follows can only reach leftwards through a chain of rules of rising rank
  in which each rule's right part begins with the previous rule's left part.
  The longest such chain, in bytes, is the merge list's sufficient lookahead
  (``MergeTable.lookahead``): tokens that end that far before the end of what has
  been read are the tokens of the whole. A boundary that stays in place makes
  both sides independent, so the rest is encoded from there on.

Every document is fed in pieces of ``PIECE_CHARS``. After each piece, what ends at a
final boundary goes out, and of an open pretoken longer than twice the lookahead
what no later byte can reach; only its last ``lookahead`` bytes are held. Memory is
bounded by the piece size, the lookahead and a word cache of fixed size, not by
the text. Decoding feeds each id's bytes to a UTF-8 state machine that
emits characters when they are complete and U+FFFD for broken sequences.

The lookahead argument needs a proper merge list (parts of a rule are made by
earlier rules); ``MergeTable`` checks that, and ``StreamEncoder`` keeps whole
pretokens where it does not hold.

Defined results: null text is encoded as empty; empty text gives no ids and decodes
to the empty text; rows are independent, so ties and repeats have no effect; extra
columns stay, and where one has the name of a result, the result's name is
lengthened by ``_``.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import json
from collections.abc import Iterator
from functools import lru_cache
from itertools import islice

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from subgraph_engine.functions.sqltools import fresh
from subgraph_engine.storage import text_batches

#: The byte-level pretoken pattern of the public tokenizer file.
PRETOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
PIECE_CHARS = 1 << 11
CACHE_WORDS = 1 << 18
CACHED_CHARS = 48
PAIR_BITS = 24


def byte_letters() -> dict[int, str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters = {b: chr(b) for b in plain}
    spare = 256
    for b in range(256):
        if b not in letters:
            letters[b] = chr(spare)
            spare += 1
    return letters


class MergeTable:
    """Vocabulary and merge list of a byte-level BPE tokenizer file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab: dict[str, int] = spec["model"]["vocab"]
        letters = byte_letters()
        self.byte_id = [vocab[letters[b]] for b in range(256)]
        back = {c: b for b, c in letters.items()}
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*vocab.values(), *self.special.values()]) + 1
        self.token_bytes: list[bytes] = [b""] * size
        for token, i in vocab.items():
            self.token_bytes[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in self.special.items():
            self.token_bytes[i] = token.encode()
        self.merges: dict[tuple[int, int], tuple[int, int]] = {}
        made = set(self.byte_id)
        self.proper = True
        self._left_of: dict[int, int] = {}
        for rank, (a, b) in enumerate(spec["model"]["merges"]):
            left, right, whole = vocab[a], vocab[b], vocab[a + b]
            self.merges[left, right] = (rank, whole)
            self.proper &= left in made and right in made and whole not in made
            made.add(whole)
            self._left_of.setdefault(whole, left)
        self.lookahead = self._sufficient_lookahead()
        self.pair_rank = {a << PAIR_BITS | b: rank for (a, b), (rank, _) in self.merges.items()}
        self.no_rank = len(spec["model"]["merges"])
        self.made = [0] * self.no_rank
        for rank, whole in self.merges.values():
            self.made[rank] = whole
        self.words: dict[str, list[int]] = {}  # ids of words seen by this process, of bounded size

    def _sufficient_lookahead(self) -> int:
        """Bytes by which a difference on the right can reach left, at most."""
        reach: dict[int, int] = {}
        for left, right in self.merges:  # in order of rank
            before, part = 0, right
            while part is not None:
                before = max(before, reach.get(part, 0))
                part = self._left_of.get(part)
            reach[left] = max(reach.get(left, 0), before + len(self.token_bytes[left]))
        return max(reach.values(), default=0)

    def encode_run(self, data: bytes) -> list[int]:
        """Ids of one pretoken."""
        ids = [self.byte_id[b] for b in data]
        return self._merge_short(ids) if len(ids) <= 64 else self._merge_long(ids)

    def _merge_short(self, ids: list[int]) -> list[int]:
        rank, none = self.pair_rank.get, self.no_rank
        ranks = [rank(a << PAIR_BITS | b, none) for a, b in zip(ids, ids[1:])]
        while ranks:
            best = min(ranks)
            if best == none:
                break
            k = ranks.index(best)
            ids[k : k + 2] = [self.made[best]]
            del ranks[k]
            if k:
                ranks[k - 1] = rank(ids[k - 1] << PAIR_BITS | ids[k], none)
            if k < len(ranks):
                ranks[k] = rank(ids[k] << PAIR_BITS | ids[k + 1], none)
        return ids

    def _merge_long(self, ids: list[int]) -> list[int]:
        """The same with a heap of candidate pairs over a linked list."""
        merges, n = self.merges, len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(merges[p][0], k, *p) for k, p in enumerate(zip(ids, ids[1:])) if p in merges]
        heapq.heapify(heap)
        gone = -1

        def offer(k: int) -> None:
            if k >= 0 and after[k] < n and (found := merges.get(pair := (ids[k], ids[after[k]]))):
                heapq.heappush(heap, (found[0], k, *pair))

        while heap:
            _, k, left, right = heapq.heappop(heap)
            j = after[k]
            if ids[k] != left or j >= n or ids[j] != right:
                continue
            ids[k], ids[j] = merges[left, right][1], gone
            after[k] = after[j]
            if after[j] < n:
                before[after[j]] = k
            offer(before[k])
            offer(k)
        return [i for i in ids if i != gone]


@lru_cache(maxsize=4)
def load_table(path: str) -> MergeTable:
    return MergeTable(path)


class RunEncoder:
    """Encodes one pretoken whose bytes come in pieces."""

    def __init__(self, table: MergeTable):
        self.table, self.held = table, b""

    def feed(self, data: bytes) -> list[int]:
        """Ids that no later byte can change; encodes again what it holds, so not before that has doubled."""
        self.held += data
        if not self.table.proper or len(self.held) <= 2 * self.table.lookahead:
            return []
        stable, out, at = len(self.held) - self.table.lookahead, [], 0
        for i in self.table.encode_run(self.held):
            end = at + len(self.table.token_bytes[i])
            if end > stable:
                break
            out.append(i)
            at = end
        self.held = self.held[at:]
        return out

    def finish(self) -> list[int]:
        rest, self.held = self.held, b""
        return self.table.encode_run(rest)


class StreamEncoder:
    """Text in pieces to ids; the ids of all pieces are those of the whole text."""

    _words = regex.compile(PRETOKEN)
    #: places where a pretoken ends whatever comes later
    _ends = regex.compile(
        r"(?<=\p{L})(?=\P{L})|(?<=\p{N})(?=\P{N})|(?<=[^\s\p{L}\p{N}])(?=\s)", flags=regex.REVERSE
    )
    #: what a pretoken that has outgrown the buffer may go on with
    _goes_on = {
        "L": regex.compile(r"\p{L}*"),
        "N": regex.compile(r"\p{N}*"),
        "O": regex.compile(r"[^\s\p{L}\p{N}]*"),
        "S": regex.compile(r"\s*"),
    }

    def __init__(self, table: MergeTable, cache: dict[str, list[int]] | None = None):
        self.table = table
        self.cache = {} if cache is None else cache
        self.held = ""
        self.run: tuple[str, RunEncoder] | None = None
        self.specials = regex.compile("|".join(map(regex.escape, table.special))) if table.special else None
        self.tail = max(map(len, table.special), default=1) - 1

    def feed(self, text: str) -> list[int]:
        self.held += text
        out: list[int] = []
        if self.run:
            out += self._continue(last=False)
            if self.run:
                return out
        if len(self.held) < PIECE_CHARS:
            return out
        limit = len(self.held) - self.tail - 1  # a special token may begin after that
        for m in self.specials.finditer(self.held) if self.specials and self._may_hold() else ():
            if m.start() <= limit < m.end():
                limit = m.start()
        cut = self._last_end(limit)
        if cut:
            out += self._segments(self.held[:cut])
            self.held = self.held[cut:]
        if len(self.held) > 2 * self.table.lookahead + self.tail:
            out += self._outgrown()
        return out

    def _may_hold(self) -> bool:
        return any(s in self.held for s in self.table.special)

    def _last_end(self, limit: int) -> int:
        """The last final boundary up to limit that lies in no special token; 0 if none."""
        spans = [m.span() for m in self.specials.finditer(self.held)] if self.specials and self._may_hold() else []
        pos = limit
        while pos > 0:
            m = self._before(pos)
            if m is None:
                return 0
            inside = next((a for a, b in spans if a < m < b), None)
            if inside is None:
                return m
            if inside == 0:
                return 0
            pos = inside
        return 0

    def _before(self, pos: int) -> int | None:
        m = self._ends.search(self.held, 0, pos + 1)
        return m.start() if m else None

    def _outgrown(self) -> list[int]:
        """Starts a run for the first pretoken, which reaches beyond the buffer."""
        if self.specials and (m := self.specials.search(self.held)):
            head, self.held = self.held[: m.end()], self.held[m.end() :]
            return self._segments(head)
        words = self._words.finditer(self.held)
        first = next(words)
        if first.end() < len(self.held) - 1 - self.tail:  # a boundary within: contractions and the like
            self.held = self.held[first.end() :]
            return self._word(first[0])
        body = self.held[1:] if self.held[0] == " " and not self.held[1].isspace() else self.held
        kind = next(k for k in "LNOS" if self._goes_on[k].match(body).end())
        self.run = (kind, RunEncoder(self.table))
        return self._continue(last=False)

    def _continue(self, last: bool) -> list[int]:
        kind, encoder = self.run
        skip = 0
        if kind != "S" and not encoder.held and self.held[:1] == " ":
            skip = 1
        end = self._goes_on[kind].match(self.held, skip).end()
        special = self.specials.search(self.held) if self.specials and kind == "O" else None
        if special and special.start() <= end:
            end = special.start()
            over = True
        else:
            over = last or end < len(self.held)
            if not over and self.specials and kind == "O":
                end = max(skip, end - self.tail)
        if kind == "S" and end == len(self.held) and not last:
            end -= 1  # the last white space may belong to the next word
        elif kind == "S" and end < len(self.held) and not special:
            end -= 1
        out = encoder.feed(self.held[: max(end, 0)].encode())
        self.held = self.held[max(end, 0) :]
        if over:
            out += encoder.finish()
            self.run = None
        return out

    def finish(self) -> list[int]:
        out = self._continue(last=True) if self.run else []
        out += self._segments(self.held)
        self.held = ""
        return out

    def _segments(self, text: str) -> list[int]:
        if not self.specials or not any(s in text for s in self.table.special):
            return self._plain(text)
        out, at = [], 0
        for m in self.specials.finditer(text):
            out += self._plain(text[at : m.start()])
            out.append(self.table.special[m[0]])
            at = m.end()
        return out + self._plain(text[at:])

    def _plain(self, text: str) -> list[int]:
        out: list[int] = []
        add, cache = out.extend, self.cache
        for word in self._words.findall(text):
            try:
                add(cache[word])
            except KeyError:
                add(self._word(word))
        return out

    def _word(self, word: str) -> list[int]:
        ids = self.table.encode_run(word.encode())
        if len(word) <= CACHED_CHARS:
            if len(self.cache) >= CACHE_WORDS:
                # words that come early are the frequent ones: the later half goes
                for late in list(islice(self.cache, CACHE_WORDS // 2, None)):
                    del self.cache[late]
            self.cache[word] = ids
        return ids


class StreamDecoder:
    """Ids in pieces to text; characters come out when their bytes are complete."""

    def __init__(self, table: MergeTable):
        self.table = table
        self.state = codecs.getincrementaldecoder("utf-8")(errors="replace")

    def feed(self, ids) -> str:
        return self.state.decode(b"".join(map(self.table.token_bytes.__getitem__, ids)))

    def finish(self) -> str:
        return self.state.decode(b"", final=True)


def encode_stream(table: MergeTable, pieces: Iterator[str], cache: dict | None = None) -> Iterator[list[int]]:
    encoder = StreamEncoder(table, cache)
    for piece in pieces:
        if ids := encoder.feed(piece):
            yield ids
    yield encoder.finish()


def _pieces(text: str) -> Iterator[str]:
    for at in range(0, len(text), PIECE_CHARS):
        yield text[at : at + PIECE_CHARS]


RESULT = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def token_digests(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens and digests of the ids and of the decoded text, per document."""
    text_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = load_table(path)
        cache = table.words
        for batch in batches:
            rows = []
            for text in batch.column("text").to_pylist():
                n, ids_hash, text_hash = 0, hashlib.sha256(), hashlib.sha256()
                decoder = StreamDecoder(table)
                for ids in encode_stream(table, _pieces(text or ""), cache):
                    n += len(ids)
                    ids_hash.update(np.array(ids, "<u4").tobytes())
                    text_hash.update(decoder.feed(ids).encode())
                text_hash.update(decoder.finish().encode())
                rows.append((n, ids_hash.hexdigest(), text_hash.hexdigest()))
            n, a, b = map(list, zip(*rows)) if rows else ([], [], [])
            columns = [batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, RESULT)


def encode(docs: DataFrame, path: str) -> DataFrame:
    """All columns of ``docs`` and, as the last three, ``token_ids`` (array of int), ``n_tokens`` and ``decoded``."""
    text_batches(docs.sparkSession)
    kept, made = docs.columns, fresh(docs, "token_ids", "n_tokens", "decoded")
    kinds = [T.ArrayType(T.IntegerType()), T.LongType(), T.StringType()]
    schema = T.StructType([*docs.schema.fields, *(T.StructField(n, k) for n, k in zip(made, kinds))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = load_table(path)
        cache = table.words
        for batch in batches:
            for part in range(0, batch.num_rows, 256):
                rows = batch.slice(part, 256)
                ids, texts = [], []
                for text in rows.column("text").to_pylist():
                    decoder, own, out = StreamDecoder(table), [], []
                    for some in encode_stream(table, _pieces(text or ""), cache):
                        own += some
                        out.append(decoder.feed(some))
                    ids.append(np.array(own, np.int32))
                    texts.append("".join(out) + decoder.finish())
                columns = [
                    *rows.columns,
                    pa.array(ids, pa.list_(pa.int32())),
                    pa.array([len(x) for x in ids], pa.int64()),
                    pa.array(texts, pa.string()),
                ]
                yield pa.RecordBatch.from_arrays(columns, [*kept, *made])

    return docs.mapInArrow(run, schema)


def byte_bpe_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def digests_of_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"), byte_bpe_path())
