"""Token-id output: ids are cut into fixed-size blocks, each block is transposed into byte or bit
planes, every plane is compressed with zstandard, and a chunk index tells where documents start.

The file format is a Parquet table written through Spark's committer (so a lost executor leaves no
half file, and any store that Spark reaches will do).  One row is one chunk of whole documents:

    part, chunk      position: chunks in (part, chunk) order hold the documents in ascending doc_id
    first_id         ids before this chunk within its part
    n_ids            ids in the chunk
    doc_ids, doc_ns  the documents of the chunk and their id counts
    sizes            compressed bytes of each plane of each block, in order
    payload          the compressed planes

Everything but `payload` is the chunk index and is read without it.

Defined cases: null text is an empty text (only the end id); rows with one doc_id, repeated or not,
all stay, ordered by a hash of the text (then the text) among themselves; a null doc_id sorts first; an empty table gives an empty
file and no rows; other columns are ignored."""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from innersearch.llm.common import bound_batches, scratch_path, text_slices, tidy

BLOCK_IDS = 16_384
CHUNK_IDS = 262_144
#: Bytes that the cache of an encoder may take, about, and the longest word that it holds.
CACHE_BYTES = 128_000_000
CACHE_WORD = 64
#: A longer text is encoded in pieces of this many bytes, cut at white space.
PIECE_BYTES = 1_000_000

CHUNK_SCHEMA = "part int, chunk int, first_id long, n_ids long, doc_ids array<long>, doc_ns array<long>, sizes array<int>, payload binary"


class Cache:
    """Ids by word or piece, in two generations: the younger one becomes the older one when it holds half of `most` bytes,
    and what is found in the older one moves up."""

    #: Bytes of an entry beside its key and its ids: two objects' heads and the place in the table.
    HEAD = 190

    def __init__(self, most: int):
        self.half, self.held = most // 2, 0
        self.now: dict = {}
        self.old: dict = {}

    def put(self, key, ids: bytes) -> None:
        if len(key) > CACHE_WORD:
            return
        self.held += len(key) + len(ids) + self.HEAD
        if self.held > self.half:
            self.old, self.now, self.held = self.now, {}, len(key) + len(ids) + self.HEAD
        self.now[key] = ids

    def again(self, key) -> bytes | None:
        """The ids of a key that the younger generation lacks."""
        ids = self.old.get(key)
        if ids is not None:
            self.put(key, ids)
        return ids


class WordEncoder:
    """Encodes whole texts with a tokenizer whose pre-tokenizer never joins characters across ASCII
    white space, remembering the ids of words and pieces in one cache bounded by bytes: a piece that
    stands as a word has the same ids.

    Words of ASCII and Latin-1 letters take a short way: lower-casing, the piece pattern of the
    vocabulary file and the BPE model itself.  All other words go through the full tokenizer."""

    #: The piece pattern of the vocabulary file over lower-case ASCII and Latin-1 letters.
    PIECE = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-zß-öø-ÿ]+|[0-9]|[^a-z0-9ß-öø-ÿ]+")
    PLAIN = re.compile(r"[!-~À-ÖØ-öø-ÿ]+")

    def __init__(self, path: str, cache_bytes: int = CACHE_BYTES):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.full = Tokenizer.from_file(path)
        self.model = self.full.model
        self.words = Cache(cache_bytes)
        visible = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
        hidden = [b for b in range(256) if b not in set(visible)]
        self.byte_chars = [""] * 256
        for b in visible:
            self.byte_chars[b] = chr(b)
        for i, b in enumerate(hidden):
            self.byte_chars[b] = chr(256 + i)
        self.id_bytes = [i.to_bytes(4, "little") for i in range(self.full.get_vocab_size())]
        self.short_way = self._short_way_holds()
        if not self.short_way:
            self.words = Cache(cache_bytes)

    def _short_way_holds(self) -> bool:
        """True if the short way gives the tokenizer's own ids on a probe of all its characters."""
        chars = [chr(c) for c in range(33, 127)] + [chr(c) for c in range(0xC0, 0x100) if c not in (0xD7, 0xF7)]
        probe = [a + b for a in chars for b in ("", "e", "T", "7", ".", "'s", "é")] + ["Don't", "WE'LL", "x'S9", "größte...", "''s"]
        return all(self._short(w) == self._long(w) for w in probe)

    def _long(self, word: str) -> bytes:
        return np.array(self.full.encode(word, add_special_tokens=False).ids, "<u4").tobytes()

    def _units(self, piece: str) -> bytes:
        """The ids of one piece by the model."""
        units = piece if piece.isascii() else "".join([self.byte_chars[b] for b in piece.encode()])
        known = self.id_bytes
        return b"".join([known[t.id] for t in self.model.tokenize(units)])

    def _piece(self, key: bytes) -> bytes:
        ids = self.words.now.get(key) or self.words.again(key)
        if ids is None:
            ids = self._units(key.decode())
            self.words.put(key, ids)
        return ids

    def _short(self, word: str) -> bytes:
        low = word.lower()
        pieces = self.PIECE.findall(low)
        if len(pieces) == 1 and low == word:  # the caller remembers it
            return self._units(word)
        return b"".join([self._piece(p.encode()) for p in pieces])

    def _made(self, raw: bytes) -> bytes:
        if self.short_way and raw.isalpha():  # ASCII letters: one piece
            low = raw.lower()
            return self._units(raw.decode()) if low == raw else self._piece(low)
        word = raw.decode()
        return self._short(word) if self.short_way and "<|" not in word and self.PLAIN.fullmatch(word) else self._long(word)

    def _word(self, raw: bytes) -> bytes:
        ids = self.words.now.get(raw) or self.words.again(raw)
        if ids is None:
            ids = self._made(raw)
            self.words.put(raw, ids)
        return ids

    def encode(self, text: bytes) -> bytes:
        """The ids of a UTF-8 text as little-endian unsigned 32-bit integers."""
        if len(text) <= PIECE_BYTES:
            return self._encoded(text)
        return b"".join([self._encoded(text[a:b]) for a, b in _pieces(text)])

    def _encoded(self, text: bytes) -> bytes:
        words = text.split()
        found = list(map(self.words.now.get, words))
        if None in found:
            make = self._word
            found = [make(w) if ids is None else ids for ids, w in zip(found, words, strict=True)]
        return b"".join(found)


_SPACE = re.compile(rb"[\x20\x09-\x0D]")


def _pieces(text: bytes) -> Iterator[tuple[int, int]]:
    """Places of pieces of PIECE_BYTES or, where no white space follows, more."""
    at = 0
    while at < len(text):
        space = _SPACE.search(text, at + PIECE_BYTES)
        end = space.start() if space else len(text)
        yield at, end
        at = end


def _planes(block: np.ndarray, kind: str) -> list[bytes]:
    rows = block.view(np.uint8).reshape(-1, 4)
    if kind == "byte":
        return [np.ascontiguousarray(rows[:, i]).tobytes() for i in range(4)]
    return [np.packbits((block >> np.uint32(i)) & np.uint32(1)).tobytes() for i in range(32)]


def pack_ids(ids: np.ndarray, block_ids: int = BLOCK_IDS, kind: str = "byte", level: int = 3) -> tuple[list[int], bytes]:
    """Compressed planes of all blocks, and the size of each."""
    import zstandard

    z = zstandard.ZstdCompressor(level=level, write_content_size=True)
    planes = [z.compress(p) for i in range(0, len(ids), block_ids) for p in _planes(ids[i : i + block_ids], kind)]
    return [len(p) for p in planes], b"".join(planes)


def unpack_ids(sizes: list[int], payload: bytes, n_ids: int, block_ids: int = BLOCK_IDS, kind: str = "byte") -> np.ndarray:
    """Inverse of pack_ids."""
    import zstandard

    z, out, at, k = zstandard.ZstdDecompressor(), np.empty(n_ids, "<u4"), 0, 0
    for i in range(0, n_ids, block_ids):
        m = min(block_ids, n_ids - i)
        if kind == "byte":
            rows = out[i : i + m].view(np.uint8).reshape(m, 4)
        else:
            block = np.zeros(m, np.uint32)
        for p in range(4 if kind == "byte" else 32):
            plane = np.frombuffer(z.decompress(payload[at : at + sizes[k]]), np.uint8)
            if kind == "byte":
                rows[:, p] = plane
            else:
                block |= np.unpackbits(plane, count=m).astype(np.uint32) << np.uint32(p)
            at, k = at + sizes[k], k + 1
        if kind != "byte":
            out[i : i + m] = block
    return out


def write_token_ids(
    docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, block_ids: int = BLOCK_IDS, chunk_ids: int = CHUNK_IDS, kind: str = "byte", level: int = 3
) -> None:
    """Encodes docs(doc_id, text) in ascending doc_id order and writes the chunks to path.

    One range shuffle of the texts; each task streams its sorted rows and holds one chunk."""
    end = int(end_id).to_bytes(4, "little")

    schema = pa.schema(
        [("part", pa.int32()), ("chunk", pa.int32()), ("first_id", pa.int64()), ("n_ids", pa.int64()), ("doc_ids", pa.list_(pa.int64())), ("doc_ns", pa.list_(pa.int64())), ("sizes", pa.list_(pa.int32())), ("payload", pa.binary())]
    )

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        coder, part = WordEncoder(tokenizer), TaskContext.get().partitionId()
        chunk = before = held = 0
        docs_, ns, parts = [], [], []

        def row() -> pa.RecordBatch:
            sizes, payload = pack_ids(np.frombuffer(b"".join(parts), "<u4"), block_ids, kind, level)
            return pa.RecordBatch.from_arrays([pa.array([v], t.type) for v, t in zip([part, chunk, before, held, docs_, ns, sizes, payload], schema, strict=True)], schema=schema)

        for batch in batches:
            texts = batch.column(1).cast(pa.large_binary())
            for i, doc in enumerate(batch.column(0).to_pylist()):
                ids = coder.encode(texts[i].as_py() or b"") + end
                docs_.append(doc)
                ns.append(len(ids) // 4)
                parts.append(ids)
                held += len(ids) // 4
                if held >= chunk_ids:
                    yield row()
                    chunk, before, held, docs_, ns, parts = chunk + 1, before + held, 0, [], [], []
            del batch, texts
        if docs_:
            yield row()

    bound_batches(docs.sparkSession)
    rows = docs.select("doc_id", "text")
    order = F.xxhash64("text")
    ordered = rows.repartitionByRange("doc_id", order).sortWithinPartitions("doc_id", order, "text")
    ordered.mapInArrow(tidy(encode), CHUNK_SCHEMA).write.option("compression", "none").parquet(path)


def read_token_ids(spark: SparkSession, path: str, block_ids: int = BLOCK_IDS, kind: str = "byte") -> DataFrame:
    """doc_id, start (ids of all documents before it), ids (little-endian unsigned 32-bit), from the files.

    The base of each part comes from the chunk index alone; it has one row for each write task.
    A task holds one chunk unpacked."""
    chunks = spark.read.schema(CHUNK_SCHEMA).parquet(path)
    totals = sorted((r[0], r[1]) for r in chunks.groupBy("part").agg(F.sum("n_ids")).collect())
    base, total = {}, 0
    for part, n in totals:
        base[part], total = total, total + n

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                part, _, first, n, doc_ids, doc_ns, sizes = (batch.column(c)[i] for c in range(7))
                ids = unpack_ids(sizes.as_py(), memoryview(batch.column(7)[i].as_buffer()), n.as_py(), block_ids, kind)
                ns = doc_ns.values.to_numpy()
                ends = np.cumsum(ns)
                starts = base[part.as_py()] + first.as_py() + ends - ns
                offsets = pa.py_buffer(np.concatenate([[0], ends * 4]).astype(np.int64))
                data = pa.Array.from_buffers(pa.large_binary(), len(ns), [None, offsets, pa.py_buffer(ids)])
                # rows are handed over in slices, so the JVM never holds a chunk of ids at once; a long document may be alone
                for at, to in text_slices(data):
                    yield pa.RecordBatch.from_arrays([doc_ids.values.slice(at, to - at), pa.array(starts[at:to], pa.int64()), data.slice(at, to - at).cast(pa.binary())], names=["doc_id", "start", "ids"])
                del ids, data
            del batch

    bound_batches(spark)
    return chunks.mapInArrow(tidy(decode), "doc_id long, start long, ids binary")


def token_digest(spark: SparkSession, docs: DataFrame, tokenizer: str) -> DataFrame:
    """Writes the ids of docs, reads the files back, and digests them per document."""
    path = scratch_path(spark, "token_ids")
    write_token_ids(docs, path, tokenizer)
    back = read_token_ids(spark, path)
    return back.select("doc_id", "start", F.floor(F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.crc32("ids").cast("long").alias("ids_crc32"))
