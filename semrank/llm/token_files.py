"""Token-id files: per-document zstandard frames over one shared dictionary, with an offset index.

Documents are dealt out by ranges of doc_id; each task encodes its texts with a public tokenizer, appends the end
id, compresses each document on its own and writes one shard. Short documents are cheap to fetch: the index at the
end of a shard gives each document's bytes, and the dictionary (trained on serialized id arrays of a bounded sample,
kept once beside the shards and named by its hash) supplies what a short frame lacks.

Shard layout, little-endian: magic ``STOK0001``; dictionary hash (32 bytes of SHA-256); id width in bytes (u32);
frames; per document doc_id (i64, with a flag byte for null), frame offset (u64), ids (u64); number of documents and
offset of the index (u64, u64); magic again.

Pieces of the tokenizer's own split are encoded once and remembered, which gives the ids that encoding the whole text
gives; texts that spell a special token go to the library whole, and so do all texts where the tokenizer's file says that
it splits, normalises, prepends or truncates in another way than the one known here (``known_split``).

Cases: a null or empty text has only the end id; repeated rows are written as often as they occur, ties of doc_id in
order of text; null doc_ids come first; an empty table gives a dictionary without training and no shard.
"""

from __future__ import annotations

import array
import gc
import hashlib
import json
import os
import re
import struct
import uuid
import zlib
from collections.abc import Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import bounded_batches, enter, file_system, new_path, only, pa_schema

#: Fixed values of the file format, the tokenizer's split pattern and the end id.
MAGIC, END_ID = b"STOK0001", 2
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Documents and bytes of the dictionary's sample, its size, and remembered pieces per generation of a worker (two are kept).
SAMPLE_DOCS, DICT_BYTES, MEMO = 512, 64 << 10, 400_000
#: The same split in the form that Python's own re runs fastest, for texts of the characters of PLAIN only
#: (ASCII and European letters: no other kind of space, no number that isn't a decimal digit).
PLAIN = r"[\t\n\r\x20-\x7E\u00A1-\u00B1\u00B4-\u00B8\u00BA\u00BB\u00BF-\u02AF]*"
_LETTERS = r"a-zA-Z\u00AA\u00B5\u00BA\u00C0-\u00D6\u00D8-\u00F6\u00F8-\u02AF"
PLAIN_SPLIT = rf" ?[{_LETTERS}]+|'(?:[stmd]|re|ve|ll)| ?[0-9]+| ?[^\s{_LETTERS}0-9]+|\s+(?!\S)|\s+"
_INDEX = np.dtype([("doc_id", "<i8"), ("null", "u1"), ("offset", "<u8"), ("n", "<u8")])
_codecs: dict[tuple, Codec] = {}


def known_split(path: str) -> bool:
    """Whether the file's tokenizer cuts a text by SPLIT and handles each piece by itself."""
    with open(path, encoding="utf-8") as f:
        told = json.load(f)
    before = told.get("pre_tokenizer") or {}
    plain = before.get("type") == "ByteLevel" and before.get("use_regex", True) and not before.get("add_prefix_space", True)
    model = told.get("model") or {}
    return plain and not any(told.get(x) for x in ("normalizer", "truncation", "padding")) and model.get("type") == "BPE" and not model.get("dropout")


class _Memo(dict):
    """Serialized ids by piece. A piece not seen lately comes from the generation before, or is encoded by the library."""

    def __init__(self, codec: Codec, before: dict):
        super().__init__()
        self.codec, self.before = codec, before

    def __missing__(self, piece: str) -> bytes:
        ids = self.before.get(piece)
        if ids is None:
            ids = self.codec._bytes(self.codec.tokenizer.encode(piece, add_special_tokens=False).ids)
        self[piece] = ids
        return ids


class Codec:
    """Texts to arrays of ids."""

    def __init__(self, path: str, end_id: int):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import regex
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special, self.by_pieces = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()], known_split(path)
        self.any_split, self.plain_split, self.plain = regex.compile(SPLIT).findall, re.compile(PLAIN_SPLIT).findall, re.compile(PLAIN).fullmatch
        self.width = 2 if max(self.tokenizer.get_vocab_size(), end_id + 1) <= 65_536 else 4
        self.end = end_id.to_bytes(self.width, "little")
        self.memo = _Memo(self, {})

    @staticmethod
    def of(path: str, end_id: int) -> Codec:
        if (path, end_id) not in _codecs:
            _codecs[path, end_id] = Codec(path, end_id)
        return _codecs[path, end_id]

    def _bytes(self, ids: list[int]) -> bytes:
        return array.array("H" if self.width == 2 else "I", ids).tobytes()

    def split(self, text: str | None) -> list[str] | None:
        """The tokenizer's own pieces; None for a text that only the library as a whole handles."""
        if not text:
            return []
        if not self.by_pieces or any(s in text for s in self.special):
            return None
        return (self.plain_split if self.plain(text) else self.any_split)(text)

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The serialized ids of each text, the end id included."""
        if len(self.memo) > MEMO:
            self.memo.before = {}
            self.memo = _Memo(self, self.memo)
        get = self.memo.__getitem__
        whole = lambda t: self._bytes(self.tokenizer.encode(t, add_special_tokens=False).ids)
        return [(whole(t) if own is None else b"".join(map(get, own))) + self.end for t, own in zip(texts, map(self.split, texts), strict=True)]


def _forget() -> None:
    _codecs.clear()


def train_dictionary(docs: DataFrame, tokenizer: str, end_id: int) -> bytes:
    """A dictionary over the ids of the documents with the smallest hashes of doc_id, as many as training asks for. Only sizes depend on it.

    From SAMPLE_DOCS documents on, four times as many are taken until their ids suffice for DICT_BYTES or all are taken;
    then the dictionary is as small as its sample asks for, or the sample itself if that is too little to train on."""
    codec, n = Codec.of(tokenizer, end_id), SAMPLE_DOCS
    while True:
        chosen = docs.select("doc_id").filter("doc_id is not null").orderBy(F.xxhash64("doc_id"), "doc_id").limit(n).distinct()
        sample = docs.join(F.broadcast(chosen), "doc_id").select("text").toLocalIterator()
        arrays = codec.encode([r["text"] for r in islice(sample, n)])
        total = sum(map(len, arrays))
        if total > 4 * DICT_BYTES or len(arrays) < n:
            break
        n *= 4
    try:
        return zstandard.train_dictionary(min(DICT_BYTES, max(total // 4, 1024)), arrays).as_bytes()
    except zstandard.ZstdError:
        # too few or too like documents to train on: their ids themselves
        content = b"".join(arrays)[-DICT_BYTES:]
        return content if len(content) >= 8 else b""


def _dictionary(data: bytes) -> zstandard.ZstdCompressionDict | None:
    return zstandard.ZstdCompressionDict(data) if data else None


def write_shards(docs: DataFrame, path: str, tokenizer: str, end_id: int = END_ID, level: int = 3) -> list[tuple[str, int, int]]:
    """Writes dictionary and shards below ``path``; (file, documents, ids) of each shard in doc_id order: one row per shard."""
    docs = only(docs, "doc_id", "text")
    bounded_batches(docs.sparkSession)
    trained = train_dictionary(docs, tokenizer, end_id)
    digest = hashlib.sha256(trained).digest()
    where, root = file_system(path)
    where.create_dir(root, recursive=True)
    with where.open_output_stream(f"{root}/dictionary-{digest.hex()}.zdict") as f:
        f.write(trained)
    shared = docs.sparkSession.sparkContext.broadcast(trained)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where, root = file_system(path)
        codec, number = Codec.of(tokenizer, end_id), TaskContext.get().partitionId()
        pack = zstandard.ZstdCompressor(level=level, dict_data=_dictionary(shared.value), write_content_size=True, write_checksum=False)
        name, out, at, index, ids = f"{root}/shard-{number:06}-{uuid.uuid4().hex}.tok", None, 0, [], 0
        enter("tokens", _forget)
        gc.disable()  # nothing here is cyclic, and the remembered pieces would be walked again and again
        try:
            for batch in batches:
                for start in range(0, batch.num_rows, 256):
                    part = batch.slice(start, 256)
                    for doc_id, data in zip(part.column(0).to_pylist(), codec.encode(part.column(1).to_pylist()), strict=True):
                        if out is None:
                            out = where.open_output_stream(name)
                            at = out.write(MAGIC + digest + struct.pack("<I", codec.width))
                        index.append((doc_id or 0, doc_id is None, at, len(data) // codec.width))
                        at += out.write(pack.compress(data))
                        ids += len(data) // codec.width
        finally:
            gc.enable()
        if out is not None:
            out.write(np.array(index, dtype=_INDEX).tobytes() + struct.pack("<QQ", len(index), at) + MAGIC)
            out.close()
            yield pa.RecordBatch.from_pydict({"shard": [number], "file": [name], "docs": [len(index)], "ids": [ids]}, schema=pa_schema("shard int, file string, docs bigint, ids bigint"))

    dealt = docs.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    return [(r["file"], r["docs"], r["ids"]) for r in sorted(dealt.mapInArrow(run, "shard int, file string, docs bigint, ids bigint").collect())]


class Shard:
    """A shard opened for reading; ``document`` fetches one document by its place in the index."""

    def __init__(self, where, name: str):
        self.file = where.open_input_file(name)
        self.size = self.file.size()
        head = self.file.read_at(44, 0)
        tail = self.file.read_at(24, self.size - 24)
        if head[:8] != MAGIC or tail[16:] != MAGIC:
            raise ValueError(f"{name} isn't a token shard")
        self.digest, self.width = head[8:40].hex(), struct.unpack("<I", head[40:44])[0]
        n, self.end = struct.unpack("<QQ", tail[:16])
        self.index = np.frombuffer(self.file.read_at(n * _INDEX.itemsize, self.end), dtype=_INDEX)
        root = name.rpartition("/")[0]
        with where.open_input_stream(f"{root}/dictionary-{self.digest}.zdict") as f:
            self.unpack = zstandard.ZstdDecompressor(dict_data=_dictionary(f.read()))

    def _bounds(self) -> np.ndarray:
        return np.append(self.index["offset"], self.end).astype(np.int64)

    def document(self, i: int) -> np.ndarray:
        a, b = self._bounds()[i : i + 2]
        return np.frombuffer(self.unpack.decompress(self.file.read_at(int(b - a), int(a))), dtype=f"<u{self.width}")

    def documents(self) -> Iterator[tuple[int | None, np.ndarray]]:
        """(doc_id, ids) of all documents in order; the file is read in pieces of some megabytes."""
        bounds, i = self._bounds(), 0
        while i < len(self.index):
            j = max(i + 1, int(np.searchsorted(bounds, bounds[i] + (8 << 20), side="right")) - 1)
            data = memoryview(self.file.read_at(int(bounds[j] - bounds[i]), int(bounds[i])))
            for k in range(i, j):
                ids = np.frombuffer(self.unpack.decompress(data[bounds[k] - bounds[i] : bounds[k + 1] - bounds[i]]), dtype=f"<u{self.width}")
                yield None if self.index["null"][k] else int(self.index["doc_id"][k]), ids
            i = j


def read_shards(spark: SparkSession, path: str, shards: list[tuple[str, int, int]]) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files alone but for the order of the shards."""
    base, rows = 0, []
    for name, _, ids in shards:
        rows.append((name, base))
        base += ids
    files = spark.createDataFrame(rows, "file string, base bigint").repartition(max(1, min(len(rows), 20_000)))
    schema = "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where, _ = file_system(path)
        for batch in batches:
            for name, start in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                out: list[tuple] = []
                for doc_id, ids in Shard(where, name).documents():
                    out.append((doc_id, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    start += len(ids)
                yield pa.RecordBatch.from_arrays([pa.array(c, type=pa.int64()) for c in zip(*out, strict=True)], schema=pa_schema(schema))

    return files.mapInArrow(run, schema)


def token_round_trip(docs: DataFrame, tokenizer: str | None = None, end_id: int = END_ID) -> DataFrame:
    """Encodes, writes and reads back; ``tokenizer`` is the path of a tokenizers file."""
    if tokenizer is None:
        import public_tokenizers

        tokenizer = public_tokenizers.path("byte_bpe_50k.json")
    path = new_path(docs.sparkSession, "tokens")
    return read_shards(docs.sparkSession, path, write_shards(docs, path, tokenizer, end_id))
