"""Token ids in files whose document boundaries and ids are Elias-Fano coded.

A shard file is: magic, ids of all its documents back to back in the narrowest unsigned type of the
vocabulary, then two Elias-Fano sequences (document ids and id-array boundaries, both ascending), then a
fixed footer with their places. A sequence of n values below u takes about 2 + log2(u/n) bits a value: low
bits packed, high bits in unary, and the place of every 256th one of these as a select structure, so that
an offset is found without a table of 64-bit numbers.

Order over files: documents are dealt to shards by ranges of doc_id; a shard's first id has as many ids
before it as all shards before it hold, which the manifest (a row per shard) tells.

Edge cases: a null text is empty, and an empty text is its end id alone; a null doc_id is ordered before all
others; rows that repeat a doc_id stand side by side, each a document, ordered by their ids' bytes; an empty
table gives no file and no rows; columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import math
import os
import struct
import uuid
import zlib
from array import array
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from crowding.llm.common import NULL_KEY, claim, keyed, open_fs, partitions, range_bounds, released, scratch, settle, slices, table, utf8

MAGIC = b"TOKEF001"
#: Every so many ones the select structure holds a place.
SELECT = 256
END_ID = 1
#: Bytes of words with their ids that a worker keeps.
CACHE = 192 << 20
#: Bytes of text a shard shall hold, and documents or ids that are read at a time.
SHARD_BYTES = 256 << 20
READ_DOCS, READ_IDS = 2048, 4 << 20
#: ASCII marks that may end a word.
TRAIL = b".,;:!?)]}|*#%$"


class EliasFano:
    """A non-decreasing sequence of non-negative integers below 2^63 in near-minimal space."""

    def __init__(self, n: int, low_bits: int, low: bytes, high: bytes, samples: np.ndarray):
        self.n, self.low_bits, self.low, self.high, self.samples = n, low_bits, low, high, samples

    @classmethod
    def encode(cls, values: np.ndarray) -> "EliasFano":
        v = np.asarray(values, dtype=np.uint64)
        n = len(v)
        if n == 0:
            return cls(0, 0, b"", b"", np.zeros(0, np.uint32))
        if np.any(v[1:] < v[:-1]):
            raise ValueError("the sequence decreases")
        low_bits = max(0, int(math.floor(math.log2((int(v[-1]) + 1) / n))))
        ones = (v >> np.uint64(low_bits)).astype(np.int64) + np.arange(n)
        bits = np.zeros(int(ones[-1]) + 1, np.uint8)
        bits[ones] = 1
        if low_bits:
            shifts = np.arange(low_bits, dtype=np.uint64)
            low = np.packbits(((v[:, None] >> shifts) & np.uint64(1)).astype(np.uint8).ravel(), bitorder="little").tobytes()
        else:
            low = b""
        return cls(n, low_bits, low, np.packbits(bits, bitorder="little").tobytes(), ones[::SELECT].astype(np.uint32))

    def _low(self, i: int) -> int:
        at = i * self.low_bits
        chunk = int.from_bytes(self.low[at // 8 : (at + self.low_bits + 7) // 8 + 1], "little")
        return chunk >> at % 8 & (1 << self.low_bits) - 1

    def select(self, i: int) -> int:
        """The i-th value: from the nearest place kept, ones are counted byte by byte."""
        if not 0 <= i < self.n:
            raise IndexError(i)
        at, left = int(self.samples[i // SELECT]), i % SELECT
        byte = self.high[at // 8] & 0xFF << at % 8
        at = at // 8
        while (c := byte.bit_count()) <= left:
            left -= c
            at += 1
            byte = self.high[at]
        for _ in range(left):
            byte &= byte - 1
        place = at * 8 + (byte & -byte).bit_length() - 1
        return place - i << self.low_bits | self._low(i)

    def values(self) -> np.ndarray:
        """All values at once."""
        if not self.n:
            return np.zeros(0, np.uint64)
        ones = np.flatnonzero(np.unpackbits(np.frombuffer(self.high, np.uint8), bitorder="little"))[: self.n]
        out = (ones - np.arange(self.n)).astype(np.uint64) << np.uint64(self.low_bits)
        if self.low_bits:
            bits = np.unpackbits(np.frombuffer(self.low, np.uint8), bitorder="little")[: self.n * self.low_bits].reshape(self.n, self.low_bits)
            out |= (bits.astype(np.uint64) << np.arange(self.low_bits, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)
        return out

    def tobytes(self) -> bytes:
        return struct.pack("<QBQQQ", self.n, self.low_bits, len(self.low), len(self.high), len(self.samples)) + self.low + self.high + self.samples.astype("<u4").tobytes()

    @classmethod
    def frombytes(cls, data: bytes) -> "EliasFano":
        n, low_bits, a, b, c = struct.unpack_from("<QBQQQ", data)
        at = struct.calcsize("<QBQQQ")
        return cls(n, low_bits, data[at : at + a], data[at + a : at + a + b], np.frombuffer(data, "<u4", c, at + a + b))


_encoders: dict[str, "WordEncoder"] = {}


class WordEncoder:
    """The tokenizers library over words cut at ASCII white space, with a bounded cache.

    Sound for tokenizers whose normalizer and pre-tokenizer see white space as a boundary, as word_bpe_49k does.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.dtype = np.dtype("<u2" if self.tok.get_vocab_size() <= 1 << 16 else "<u4")
        self.known: dict[bytes, bytes] = {}
        self.held = 0
        # whether upper case and words of ASCII letters are seen to go the way that the shortcuts below take
        probe = "Abc xyzzy the WORD"
        ids = self.tok.encode(probe.lower(), add_special_tokens=False).ids
        self.plain = self.tok.encode(probe, add_special_tokens=False).ids == ids == [t.id for w in probe.lower().split() for t in self.tok.model.tokenize(w)]

    @classmethod
    def of(cls, path: str) -> "WordEncoder":
        if path not in _encoders:
            _encoders[path] = cls(path)
        claim(f"words {path}", _encoders[path].forget)
        return _encoders[path]

    def forget(self) -> None:
        self.known.clear()
        self.held = 0

    def _learn(self, missing: set[bytes]) -> None:
        """Ids of words; end punctuation behind a letter is a piece of its own to these tokenizers."""
        known, cut, need = self.known, {}, set()
        for w in missing:
            core = w.rstrip(TRAIL)
            if len(core) < len(w) and core and (core[-1:].isalpha() or (core[-1] > 127 and core.decode()[-1].isalpha())):
                cut[w] = core
                need.add(core)
                need.add(w[len(core) :])
            else:
                need.add(w)
        whole = []
        model, dtype = self.tok.model, self.dtype
        for w in need.difference(known):
            if self.plain and w.isalpha() and w.islower():  # ASCII letters in lower case: neither normalizer nor splitter change them
                known[w] = array(dtype.char, [t.id for t in model.tokenize(w.decode())]).tobytes()
            else:
                whole.append(w)
        for i in range(0, len(whole), 4096):
            part = whole[i : i + 4096]
            for w, e in zip(part, self.tok.encode_batch_fast([w.decode() for w in part], add_special_tokens=False)):
                known[w] = array(dtype.char, e.ids).tobytes()
        for w, core in cut.items():
            known[w] = known[core] + known[w[len(core) :]]
        self.held += sum(170 + 4 * len(w) for w in chain(need, cut))  # entry, word and ids, about

    def encode(self, texts: list[bytes]) -> list[bytes]:
        """Ids of each text, back to back in dtype."""
        known = self.known
        if self.held > CACHE:
            self.forget()
        # lower case is the tokenizer's own doing; only the strings of added tokens must keep theirs
        cut = [(t.lower() if self.plain and b"<|" not in t else t).split() for t in texts]
        missing = set().union(*cut).difference(known)
        if missing:
            self._learn(missing)
        get = known.__getitem__
        return [b"".join(map(get, words)) for words in cut]


def encode_documents(docs: DataFrame, tokenizer: str, end_id: int, bounds: list[int]) -> DataFrame:
    """shard, key, ids (binary): ids of each text and the end id; a shard is a range of keys."""
    cuts = np.array(bounds, np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = WordEncoder.of(tokenizer)
        end = np.array([end_id], enc.dtype).tobytes()
        for b in slices(batches, 1024, 8 << 20):
            ids = [x + end for x in enc.encode(utf8(b, "text"))]
            shard = np.searchsorted(cuts, b.column("key").to_numpy(zero_copy_only=False), side="right").astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(shard), b.column("key"), pa.array(ids, pa.binary())], names=["shard", "key", "ids"])

    return docs.mapInArrow(released(run), "shard int, key long, ids binary")


def write_shards(encoded: DataFrame, root: str, width: int) -> DataFrame:
    """Write each shard's file; manifest (shard, path, n_docs, n_ids). encoded: sorted by shard, key within partitions.

    Ids are written as they come; of a document 16 bytes are held until its shard is closed.
    """

    def close(f, shard, path, keys: array, sizes: array):
        at = np.concatenate([[0], np.cumsum(np.frombuffer(sizes, np.int64))]).astype(np.uint64)
        first = keys[0]
        ids = EliasFano.encode(np.frombuffer(keys, np.int64).astype(np.uint64) - np.uint64(first % 2**64)).tobytes()
        edges = EliasFano.encode(at).tobytes()
        f.write(ids + edges + struct.pack("<qQQQB", first, int(at[-1]), len(ids), len(edges), width) + MAGIC)
        f.close()
        return pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([path]), pa.array([len(keys)], pa.int64()), pa.array([int(at[-1])], pa.int64())], names=["shard", "path", "n_docs", "n_ids"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, top = open_fs(root)
        fs.create_dir(top, recursive=True)
        f, now, path, keys, sizes = None, None, "", array("q"), array("q")
        for b in batches:
            for shard, key, ids in zip(*(b.column(c).to_pylist() for c in ("shard", "key", "ids"))):
                if shard != now or f is None:
                    if f is not None:
                        yield close(f, now, path, keys, sizes)
                    now, path, keys, sizes = shard, f"{shard:06d}-{uuid.uuid4().hex}.tokef", array("q"), array("q")
                    f = fs.open_output_stream(f"{top}/{path}", buffer_size=1 << 20)
                    f.write(MAGIC)
                f.write(ids)
                keys.append(key)
                sizes.append(len(ids) // width)
        if f is not None:
            yield close(f, now, path, keys, sizes)

    return encoded.mapInArrow(released(run), "shard int, path string, n_docs long, n_ids long")


class ShardFile:
    """A shard opened for reading: offsets by select, ids of any document by place."""

    def __init__(self, uri: str):
        fs, path = open_fs(uri)
        self.file = fs.open_input_file(path)
        size, tail = self.file.size(), struct.calcsize("<qQQQB") + 8
        foot = self.file.read_at(tail, size - tail)
        if foot[-8:] != MAGIC:
            raise ValueError("not a token shard")
        self.first, self.n_ids, a, b, self.width = struct.unpack_from("<qQQQB", foot)
        self.keys = EliasFano.frombytes(self.file.read_at(a, size - tail - a - b))
        self.edges = EliasFano.frombytes(self.file.read_at(b, size - tail - b))
        self.dtype = np.dtype(f"<u{self.width}")

    def __len__(self) -> int:
        return self.keys.n

    def key(self, i: int) -> int:
        return self.keys.select(i) + self.first

    def span(self, i: int) -> tuple[int, int]:
        return self.edges.select(i), self.edges.select(i + 1)

    def read(self, start: int, stop: int) -> np.ndarray:
        return np.frombuffer(self.file.read_at((stop - start) * self.width, len(MAGIC) + start * self.width), self.dtype)

    def ids(self, i: int) -> np.ndarray:
        return self.read(*self.span(i))


def read_shards(spark: SparkSession, manifest: DataFrame, root: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files; offsets and ids of documents by select."""
    by = W.orderBy("shard").rowsBetween(W.unboundedPreceding, -1)
    base = F.coalesce(F.sum("n_ids").over(by), F.lit(0)).cast("long")  # a row per shard
    files = manifest.select(F.concat(F.lit(f"{root}/"), "path").alias("path"), base.alias("base"), "shard")
    files = settle(files, "token-bases")
    files = files.repartition(max(1, files.count()), "shard").select("path", "base")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for path, start in zip(b.column("path").to_pylist(), b.column("base").to_pylist()):
                s = ShardFile(path)
                i, at = 0, 0
                while i < len(s):
                    cut = [at]
                    while len(cut) <= READ_DOCS and i + len(cut) <= len(s) and cut[-1] - at < READ_IDS:
                        cut.append(s.edges.select(i + len(cut)))
                    n = len(cut) - 1
                    mem = memoryview(s.read(cut[0], cut[-1]).astype("<u4")).cast("B")
                    crc = [zlib.crc32(mem[4 * (a - at) : 4 * (e - at)]) for a, e in zip(cut, cut[1:])]
                    ids = [None if (k := s.key(j)) == NULL_KEY else k for j in range(i, i + n)]
                    places = np.array(cut, np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(places[:-1] + start), pa.array(np.diff(places)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])
                    i, at = i + n, cut[-1]

    return files.mapInArrow(released(run), "doc_id long, start long, n_tokens long, ids_crc32 long")


def write_token_files(docs: DataFrame, tokenizer: str, root: str, end_id: int = END_ID, shards: int | None = None) -> DataFrame:
    """Encode documents to shard files below a shared path; the manifest, settled. Shards grow in number with the bytes of text."""
    spark = docs.sparkSession
    rows = keyed(docs)
    if shards is None:
        total = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
        shards = max(partitions(spark), int(total) // SHARD_BYTES + 1)
    bounds = range_bounds(rows.select("key"), "key", shards)
    width = WordEncoder.of(tokenizer).dtype.itemsize
    dealt = encode_documents(rows, tokenizer, end_id, bounds).repartition(len(bounds) + 1, "shard").sortWithinPartitions("shard", "key", "ids")
    return settle(write_shards(dealt, root, width), "token-manifest")


def op8_elias_fano(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents' ids written as shard files, and what the files say of each document."""
    import public_tokenizers

    root = scratch(spark, "token-files")
    manifest = write_token_files(table(spark, sf_dir, "documents"), str(public_tokenizers.path("word_bpe_49k.json")), root)
    return read_shards(spark, manifest, root)
