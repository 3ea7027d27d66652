"""Media columns: ISO base media containers, written, walked and described without decoding a payload.

``encode`` puts bytes into a container with one uncompressed 8-bit mono track, whose sync table marks the first
sample of every chunk as a place to start from; ``describe`` walks the nested boxes of any such container, decodes the
sample tables (sizes, chunks, durations, sync samples) and gives codec, duration and the byte range of each keyframe
as typed columns. Containers are kept in a binary column of a stored table.

Cases: a null text is an empty one; empty texts give one block of zero bytes; rows are handled one by one, so
repeated rows give repeated results; a column that is null or isn't a container is described as codec "none", without
duration or ranges, and its payload is empty; a table that claims more entries than its box holds is read as empty and
a range that reaches beyond the file is left out, and either makes the row ``broken``; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import itertools
import struct
import zlib
from bisect import bisect_left
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import as_bytes, only, per_batch, stored

#: The sample rate, samples to a chunk, and boxes that hold other boxes; how deep boxes may nest.
RATE, CHUNK, BLOCK, DEPTH = 8000, 4096, 64, 16
_NESTS = {b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf", b"edts", b"udta"}


def _box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    return struct.pack(">I", len(body) + 8) + kind + body


def _full(kind: bytes, body: bytes, flags: int = 0) -> bytes:
    return _box(kind, struct.pack(">I", flags), body)


def padded(text: bytes) -> bytes:
    """The bytes, filled up with zeros to a positive multiple of BLOCK."""
    return text + b"\0" * (-len(text) % BLOCK if text else BLOCK)


def encode(payload: bytes) -> bytes:
    """A container whose only track holds the payload as unsigned 8-bit samples at RATE."""
    n = len(payload)
    chunks = [min(CHUNK, n - i) for i in range(0, n, CHUNK)]
    matrix = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)
    head = _box(b"ftyp", b"isom", struct.pack(">I", 512), b"isomiso2mp41")

    def movie(base: int) -> bytes:
        offsets, at = [], base
        for c in chunks:
            offsets.append(at)
            at += c
        runs = [(1, chunks[0])] if chunks else []
        if len(chunks) > 1 and chunks[-1] != chunks[0]:
            runs.append((len(chunks), chunks[-1]))
        stbl = _box(
            b"stbl",
            _full(b"stsd", struct.pack(">I", 1) + _box(b"raw ", bytes(6), struct.pack(">HIIHHHHI", 1, 0, 0, 1, 8, 0, 0, RATE << 16))),
            _full(b"stts", struct.pack(">III", 1, n, 1)),
            _full(b"stsc", struct.pack(">I", len(runs)) + b"".join(struct.pack(">III", first, count, 1) for first, count in runs)),
            _full(b"stsz", struct.pack(">II", 1, n)),
            _full(b"stss", struct.pack(f">I{len(chunks)}I", len(chunks), *range(1, n + 1, CHUNK))),
            _full(b"co64", struct.pack(f">I{len(offsets)}Q", len(offsets), *offsets)),
        )
        minf = _box(b"minf", _full(b"smhd", bytes(4)), _box(b"dinf", _full(b"dref", struct.pack(">I", 1) + _full(b"url ", b"", 1))), stbl)
        mdia = _box(b"mdia", _full(b"mdhd", struct.pack(">IIIIHH", 0, 0, RATE, n, 0x55C4, 0)), _full(b"hdlr", bytes(4) + b"soun" + bytes(13)), minf)
        tkhd = _full(b"tkhd", struct.pack(">IIIII", 0, 0, 1, 0, n) + bytes(8) + struct.pack(">HHHH", 0, 0, 0x100, 0) + matrix + bytes(8), 7)
        mvhd = _full(b"mvhd", struct.pack(">IIIIIH", 0, 0, RATE, n, 0x10000, 0x100) + bytes(10) + matrix + bytes(24) + struct.pack(">I", 2))
        return _box(b"moov", mvhd, _box(b"trak", tkhd, mdia))

    start = len(head) + len(movie(0)) + 16
    return head + movie(start) + struct.pack(">I4sQ", 1, b"mdat", n + 16) + payload


@dataclass
class Track:
    handler: str = ""
    codec: str = ""
    scale: int = 0
    duration: int = 0
    width: int = 0
    height: int = 0
    times: list[tuple[int, int]] = field(default_factory=list)
    chunk_runs: list[tuple[int, int]] = field(default_factory=list)
    fixed_size: int = 0
    n_samples: int = 0
    sizes: tuple[int, ...] = ()
    chunks: tuple[int, ...] = ()
    sync: tuple[int, ...] | None = None
    broken: bool = False

    def chunk_ranges(self) -> list[tuple[int, int, int]]:
        """(offset, bytes, samples) of each chunk."""
        out, sample, run = [], 0, 0
        for i, offset in enumerate(self.chunks, 1):
            while run + 1 < len(self.chunk_runs) and self.chunk_runs[run + 1][0] <= i:
                run += 1
            count = min(self.chunk_runs[run][1], self.n_samples - sample) if self.chunk_runs else 0
            size = self.fixed_size * count if self.fixed_size else sum(self.sizes[sample : sample + count])
            out.append((offset, size, count))
            sample += count
        return out

    def keyframes(self) -> list[tuple[int, int]]:
        """(offset, bytes) of the sync samples; where every sample is one, neighbouring samples are one range."""
        chunks = self.chunk_ranges()
        if self.sync is None:
            ranges: list[list[int]] = []
            for offset, size, _ in chunks:
                if ranges and sum(ranges[-1]) == offset:
                    ranges[-1][1] += size
                elif size:
                    ranges.append([offset, size])
            return [(a, b) for a, b in ranges]
        wanted, out, first = sorted(set(self.sync)), [], 1
        for offset, _, count in chunks:
            at = first
            for sample in wanted[bisect_left(wanted, first) : bisect_left(wanted, first + count)]:
                offset += self.fixed_size * (sample - at) if self.fixed_size else sum(self.sizes[at - 1 : sample - 1])
                out.append((offset, self.fixed_size or self.sizes[sample - 1]))
                at = sample
            first += count
        return out

    def duration_ms(self) -> int | None:
        return self.duration * 1000 // self.scale if self.scale else None


def boxes(data: bytes, start: int = 0, end: int | None = None):
    """(type, start of the body, end) of the boxes at one level; sizes that don't fit end the walk."""
    at, end = start, len(data) if end is None else end
    while at + 8 <= end:
        size, kind = struct.unpack_from(">I4s", data, at)
        body = at + 8
        if size == 1 and at + 16 <= end:
            size, body = struct.unpack_from(">Q", data, body)[0], at + 16
        size = end - at if size == 0 else size
        if size < body - at or at + size > end:
            return
        yield kind, body, at + size
        at += size


def _entries(data: bytes, at: int, end: int, n: int, kinds: str) -> list[tuple] | None:
    """n entries of a table, None where the box doesn't hold so many."""
    size = struct.calcsize(">" + kinds)
    return list(struct.iter_unpack(">" + kinds, data[at : at + size * n])) if at + size * n <= end else None


def tracks(data: bytes) -> list[Track]:
    """Every track of the container, from its sample tables alone."""
    found: list[Track] = []

    def walk(start: int, end: int | None, depth: int) -> None:
        for kind, a, b in boxes(data, start, end):
            if kind == b"trak":
                found.append(Track())
            if kind in _NESTS:
                if depth < DEPTH:
                    walk(a, b, depth + 1)
            elif found and b - a >= 8:
                read(found[-1], kind, a, b)

    def read(t: Track, kind: bytes, a: int, b: int) -> None:
        if kind == b"mdhd":
            wide = data[a] == 1
            got = _entries(data, a + (20 if wide else 12), b, 1, "IQ" if wide else "II")
            (t.scale, t.duration), t.broken = got[0] if got else (0, 0), t.broken or not got
        elif kind == b"hdlr" and b - a >= 12:
            t.handler = data[a + 8 : a + 12].decode("latin-1")
        elif kind == b"stsd" and b - a >= 16:
            t.codec = data[a + 12 : a + 16].decode("latin-1").strip()
            if t.handler == "vide" and b - a >= 44:
                t.width, t.height = struct.unpack_from(">HH", data, a + 40)
        elif kind == b"stsz" and b - a >= 12:
            t.fixed_size, t.n_samples = struct.unpack_from(">II", data, a + 4)
            sizes = () if t.fixed_size else _entries(data, a + 12, b, t.n_samples, "I")
            t.sizes = tuple(itertools.chain.from_iterable(sizes or ()))
            if sizes is None:
                t.n_samples, t.broken = 0, True
        elif kind in (b"stco", b"co64", b"stss", b"stts", b"stsc"):
            form = {b"co64": "Q", b"stts": "II", b"stsc": "III"}.get(kind, "I")
            rows = _entries(data, a + 8, b, struct.unpack_from(">I", data, a + 4)[0], form)
            t.broken |= rows is None
            rows = rows or []
            if kind == b"stts":
                t.times = rows
            elif kind == b"stsc":
                t.chunk_runs = [r[:2] for r in rows]
            elif kind == b"stss":
                t.sync = tuple(r[0] for r in rows)
            else:
                t.chunks = tuple(r[0] for r in rows)

    walk(0, None, 0)
    return found


def described(data: bytes | None) -> dict:
    """codec, handler, duration_ms and n_samples of the first track, n_tracks, all keyframe ranges track by track, broken."""
    own = tracks(data or b"")
    ranges = [(i, a, n) for i, t in enumerate(own) for a, n in t.keyframes()]
    inside = [(i, a, n) for i, a, n in ranges if a + n <= len(data or b"")]
    first = own[0] if own else Track(codec="none")
    return {
        "codec": first.codec, "handler": first.handler, "duration_ms": first.duration_ms(), "n_samples": first.n_samples, "n_tracks": len(own),
        "keyframe_tracks": [i for i, _, _ in inside], "keyframe_offsets": [a for _, a, _ in inside], "keyframe_lengths": [n for _, _, n in inside],
        "broken": len(inside) < len(ranges) or any(t.broken for t in own),
    }


def describe(data: bytes | None) -> str:
    """One text for all tracks: codec, duration in milliseconds, samples, and every keyframe range."""
    out = []
    for t in tracks(data or b""):
        keys = t.keyframes()
        out.append(f"codec={t.codec};handler={t.handler};ms={t.duration_ms() or 0};samples={t.n_samples};keyframes={len(keys)};ranges={','.join(f'{a}+{n}' for a, n in keys)}")
    return "|".join(out) or "codec=none"


def stored_samples(data: bytes | None) -> bytes:
    """The bytes of the first track's samples, cut out by its chunk table."""
    return b"".join(data[a : a + n] for a, n, _ in next(iter(tracks(data or b"")), Track()).chunk_ranges())


def media_column(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, media: each text as a container."""

    def make(batch: pa.RecordBatch) -> dict:
        texts = [t or b"" for t in as_bytes(batch)]
        return {"doc_id": batch.column(0), "n_bytes": [len(t) for t in texts], "media": [encode(padded(t)) for t in texts]}

    return per_batch(only(docs, "doc_id", "text"), make, "doc_id bigint, n_bytes bigint, media binary")


_FEATURES = (
    "payload_bytes bigint, payload_sha256 string, tail_crc32 bigint, media_bytes bigint, media_sha256 string, feature string, codec string, handler string, duration_ms bigint, "
    "n_samples bigint, n_tracks int, keyframe_tracks array<int>, keyframe_offsets array<bigint>, keyframe_lengths array<bigint>, broken boolean"
)


def media_features(media: DataFrame) -> DataFrame:
    """doc_id, n_bytes and what the column ``media`` holds: codec, duration and all keyframe ranges as typed columns."""
    names = [x.split(" ")[0] for x in _FEATURES.split(", ")]

    def make(batch: pa.RecordBatch) -> dict:
        out: dict = {n: [] for n in names}
        for data in batch.column(2).to_pylist():
            payload = stored_samples(data)
            row = {"payload_bytes": len(payload), "payload_sha256": hashlib.sha256(payload).hexdigest(), "tail_crc32": zlib.crc32(payload[-BLOCK:]), "media_bytes": len(data or b""), "media_sha256": hashlib.sha256(data or b"").hexdigest(), "feature": describe(data), **described(data)}
            for name in names:
                out[name].append(row[name])
        return {"doc_id": batch.column(0), "n_bytes": batch.column(1), **out}

    return per_batch(media.select("doc_id", "n_bytes", "media"), make, "doc_id bigint, n_bytes bigint, " + _FEATURES)


def media_round_trip(docs: DataFrame) -> DataFrame:
    """Stores the containers as a table of the shared folder, reads them back and describes them."""
    return media_features(stored(media_column(docs), "media"))
