"""Media columns: payloads kept in ISO media containers, described from their boxes alone.

``build`` writes a container whose single audio track holds the payload as unsigned 8-bit samples in blocks of 64, 64 blocks a
chunk, the first block of each chunk being a key frame.  ``describe`` walks the nested boxes of any such container, decodes the
sample tables, those of movie fragments as well, and returns codec, time scale, duration, and the byte ranges of samples and key
frames of every track; it skips ``mdat``.

Defined cases: a null or empty text is a payload of one block of zeros; equal texts give equal bytes; a container that is cut
short or malformed gives ``ValueError`` (column form: null codec and the message in ``error``), and so does one whose tables tell
of more samples than it has bytes, or whose fragment belongs to no track; a track's duration is that of its header, if known,
plus that of its fragments.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from sharetree.llm.storage import materialize

BLOCK, BLOCKS_PER_CHUNK, TIME_SCALE = 64, 64, 8000
# Fixed values of the container format: boxes that hold boxes.
CONTAINERS = {b"moov", b"trak", b"mdia", b"minf", b"stbl", b"dinf", b"edts", b"udta", b"mvex", b"moof", b"traf"}
MATRIX = struct.pack(">9I", 0x10000, 0, 0, 0, 0x10000, 0, 0, 0, 0x40000000)
FEATURES_SCHEMA = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"


def padded(text: bytes) -> bytes:
    return text + bytes(-len(text) % BLOCK if text else BLOCK)


def _box(kind: bytes, *parts: bytes) -> bytes:
    body = b"".join(parts)
    return struct.pack(">I", 8 + len(body)) + kind + body


def _full(kind: bytes, *parts: bytes, flags: int = 0) -> bytes:
    return _box(kind, struct.pack(">I", flags), *parts)


def build(payload: bytes) -> bytes:
    """A container that holds ``payload``, whose length is a positive multiple of the block."""
    blocks = len(payload) // BLOCK
    if blocks < 1 or len(payload) % BLOCK:
        raise ValueError("the payload is no positive multiple of the block")
    chunks, last = -(-blocks // BLOCKS_PER_CHUNK), blocks % BLOCKS_PER_CHUNK
    runs = [(1, BLOCKS_PER_CHUNK)] if chunks > 1 or not last else []
    runs += [(chunks, last)] if last else []
    ftyp = _box(b"ftyp", b"isom", struct.pack(">I", 512), b"isomiso2mp41")
    entry = _box(b"raw ", bytes(6), struct.pack(">H", 1), bytes(8), struct.pack(">HHHHI", 1, 8, 0, 0, TIME_SCALE << 16))
    wide = len(payload) + 4096 + 12 * chunks > 0xFFFFFFF0
    duration = len(payload)  # a sample is a byte

    def moov(first: int) -> bytes:
        offsets = np.arange(chunks, dtype=np.uint64) * (BLOCK * BLOCKS_PER_CHUNK) + first
        keys = np.arange(chunks, dtype=np.uint32) * BLOCKS_PER_CHUNK + 1
        table = _box(
            b"stbl",
            _full(b"stsd", struct.pack(">I", 1), entry),
            _full(b"stts", struct.pack(">III", 1, blocks, BLOCK)),
            _full(b"stsc", struct.pack(">I", len(runs)), *(struct.pack(">III", c, n, 1) for c, n in runs)),
            _full(b"stsz", struct.pack(">II", BLOCK, blocks)),
            _full(b"co64", struct.pack(">I", chunks), offsets.astype(">u8").tobytes()) if wide else _full(b"stco", struct.pack(">I", chunks), offsets.astype(">u4").tobytes()),
            _full(b"stss", struct.pack(">I", chunks), keys.astype(">u4").tobytes()),
        )
        media = _box(
            b"mdia",
            _box(b"mdhd", struct.pack(">I", 1 << 24), bytes(16), struct.pack(">IQ", TIME_SCALE, duration), struct.pack(">HH", 0x55C4, 0)),
            _full(b"hdlr", bytes(4), b"soun", bytes(12), b"text as samples\0"),
            _box(b"minf", _full(b"smhd", bytes(4)), _box(b"dinf", _full(b"dref", struct.pack(">I", 1), _full(b"url ", flags=1))), table),
        )
        track = _box(b"trak", _box(b"tkhd", struct.pack(">I", 1 << 24 | 7), bytes(16), struct.pack(">IIQ", 1, 0, duration), bytes(8), struct.pack(">HHHH", 0, 0, 0x100, 0), MATRIX, bytes(8)), media)
        movie = _box(b"mvhd", struct.pack(">I", 1 << 24), bytes(16), struct.pack(">IQ", TIME_SCALE, duration), struct.pack(">IHH", 0x10000, 0x100, 0), bytes(8), MATRIX, bytes(24), struct.pack(">I", 2))
        return _box(b"moov", movie, track)

    mdat = struct.pack(">I4sQ", 1, b"mdat", 16 + len(payload)) if wide else struct.pack(">I4s", 8 + len(payload), b"mdat")
    start = len(ftyp) + len(moov(0)) + len(mdat)
    return ftyp + moov(start) + mdat + payload


@dataclass
class Track:
    codec: str = ""
    handler: str = ""
    time_scale: int = 0
    duration: int = 0
    number: int = 0
    room: int = 0
    tables: dict[bytes, memoryview] = field(default_factory=dict)
    #: Offsets, sizes and whether they are key frames, of the samples of each run of a fragment.
    runs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = field(default_factory=list)

    def _sizes(self) -> np.ndarray:
        """The size table, in its plain or its compact form."""
        if b"stsz" in self.tables:
            size, n = struct.unpack_from(">II", self.tables[b"stsz"], 4)
            if n > self.room:
                raise ValueError("more samples than bytes")
            return np.full(n, size, np.int64) if size else np.frombuffer(self.tables[b"stsz"], ">u4", n, 12).astype(np.int64)
        if b"stz2" in self.tables:
            bits, n = struct.unpack_from(">II", self.tables[b"stz2"], 4)
            bits &= 0xFF
            if bits == 4:
                pairs = np.frombuffer(self.tables[b"stz2"], np.uint8, (n + 1) // 2, 12)
                return np.stack((pairs >> 4, pairs & 15), 1).ravel()[:n].astype(np.int64)
            if bits not in (8, 16):
                raise ValueError("a size table of unknown width")
            return np.frombuffer(self.tables[b"stz2"], f">u{bits // 8}", n, 12).astype(np.int64)
        return np.zeros(0, np.int64)

    def _tabled(self) -> tuple[np.ndarray, np.ndarray]:
        """Offset and size of the samples that the size, chunk and offset tables tell of."""
        sizes = self._sizes()
        n = len(sizes)
        if not n:
            return sizes, sizes
        kind = b"co64" if b"co64" in self.tables else b"stco"
        (chunks,) = struct.unpack_from(">I", self.tables[kind], 4)
        offsets = np.frombuffer(self.tables[kind], ">u8" if kind == b"co64" else ">u4", chunks, 8).astype(np.int64)
        (runs,) = struct.unpack_from(">I", self.tables[b"stsc"], 4)
        table = np.frombuffer(self.tables[b"stsc"], ">u4", 3 * runs, 8).reshape(runs, 3).astype(np.int64)
        per_chunk = np.repeat(table[:, 1], np.diff(np.append(table[:, 0], chunks + 1)))
        if len(per_chunk) != chunks or per_chunk.sum() < n:
            raise ValueError("sample tables disagree")
        chunk = np.repeat(np.arange(chunks), per_chunk)[:n]
        ends = np.cumsum(sizes)
        first = np.concatenate(([0], np.cumsum(per_chunk)))[:-1][chunk]
        return offsets[chunk] + (ends - sizes) - (ends - sizes)[first], sizes

    def samples(self) -> tuple[np.ndarray, np.ndarray]:
        """Offset and size of every sample, those of fragments last."""
        offsets, sizes = zip(self._tabled(), *((o, s) for o, s, _ in self.runs))
        return np.concatenate(offsets), np.concatenate(sizes)

    def keys(self) -> np.ndarray:
        """Numbers of the key frames, from 0; without a table every sample is one."""
        n = len(self._sizes())
        if b"stss" in self.tables:
            (some,) = struct.unpack_from(">I", self.tables[b"stss"], 4)
            numbers = np.frombuffer(self.tables[b"stss"], ">u4", some, 8).astype(np.int64) - 1
        else:
            numbers = np.arange(n)
        marks = [k for _, _, k in self.runs]
        return np.concatenate((numbers, n + np.flatnonzero(np.concatenate(marks)))) if marks else numbers


def walk(data: memoryview, start: int = 0, stop: int | None = None) -> Iterator[tuple[bytes, int, int, int]]:
    """(type, box start, content start, stop) of each box, depth first; containers are entered, payloads are not read."""
    stop = len(data) if stop is None else stop
    while start < stop:
        if stop - start < 8:
            raise ValueError("a box is cut short")
        size, kind = struct.unpack_from(">I4s", data, start)
        head = 8
        if size == 1:
            if stop - start < 16:
                raise ValueError("a box is cut short")
            (size,), head = struct.unpack_from(">Q", data, start + 8), 16
        elif size == 0:
            size = stop - start
        if size < head or start + size > stop:
            raise ValueError("a box is larger than what holds it")
        yield kind, start, start + head, start + size
        if kind in CONTAINERS:
            yield from walk(data, start + head, start + size)
        start += size


@dataclass
class Fragment:
    """What the boxes of a movie fragment have said so far."""

    start: int  # of the fragment's box
    end: int  # of the data told of
    base: int = 0
    number: int = 0
    #: Duration, size and flags of samples that don't give their own.
    values: list[int] = field(default_factory=list)

    def head(self, view: memoryview, at: int, defaults: dict[int, list[int]]) -> None:
        flags, self.number = struct.unpack_from(">II", view, at)
        self.values = list(defaults.get(self.number, (0, 0, 0)))
        self.base = self.start if flags & 0x20000 else self.end
        at += 8
        if flags & 1:
            (self.base,) = struct.unpack_from(">Q", view, at)
            at += 8
        at += 4 if flags & 2 else 0
        for i, bit in enumerate((0x8, 0x10, 0x20)):
            if flags & bit:
                (self.values[i],) = struct.unpack_from(">I", view, at)
                at += 4
        self.end = self.base

    def run(self, view: memoryview, at: int, stop: int, track: Track) -> None:
        """Gives the track the samples of a run."""
        flags, n = struct.unpack_from(">II", view, at)
        at += 8
        if flags & 1:
            self.end = self.base + struct.unpack_from(">i", view, at)[0]
            at += 4
        first = None
        if flags & 4:
            (first,) = struct.unpack_from(">I", view, at)
            at += 4
        given = [i for i, bit in enumerate((0x100, 0x200, 0x400, 0x800)) if flags & bit]
        if n > len(view) or at + 4 * n * len(given) > stop:
            raise ValueError("more samples than bytes")
        table = np.frombuffer(view, ">u4", n * len(given), at).reshape(n, len(given)).astype(np.int64)
        durations, sizes, marks = (table[:, given.index(i)] if i in given else np.full(n, self.values[i], np.int64) for i in range(3))
        if first is not None:
            marks[:1] = first
        ends = self.end + np.cumsum(sizes)
        track.runs.append((ends - sizes, sizes, (marks & 0x10000) == 0))
        track.duration += int(durations.sum())
        self.end += int(sizes.sum())


def describe(data: bytes) -> list[Track]:
    """The tracks of a container."""
    view, tracks = memoryview(data), []
    defaults: dict[int, list[int]] = {}
    fragment = Fragment(0, 0)
    try:
        for kind, start, a, b in walk(view):
            if kind == b"trak":
                tracks.append(Track(room=len(view)))
            elif kind == b"trex":
                number, _, *defaults[number] = struct.unpack_from(">5I", view, a + 4)
            elif kind == b"moof":
                fragment = Fragment(start, start)
            elif kind == b"tfhd":
                fragment.head(view, a, defaults)
            elif kind == b"trun":
                owner = next((t for t in tracks if t.number == fragment.number), None)
                if owner is None:
                    raise ValueError("a fragment of no track")
                fragment.run(view, a, b, owner)
            elif not tracks:
                continue
            elif kind == b"tkhd":
                (tracks[-1].number,) = struct.unpack_from(">I", view, a + (20 if view[a] == 1 else 12))
            elif kind == b"mdhd":
                wide = view[a] == 1
                tracks[-1].time_scale, duration = struct.unpack_from(">IQ" if wide else ">II", view, a + (20 if wide else 12))
                tracks[-1].duration = 0 if duration == (1 << (64 if wide else 32)) - 1 else duration  # all ones: not known
            elif kind == b"hdlr":
                tracks[-1].handler = bytes(view[a + 8 : a + 12]).decode("latin-1")
            elif kind == b"stsd":
                tracks[-1].codec = bytes(view[a + 12 : a + 16]).decode("latin-1")
            elif kind in (b"stts", b"stsc", b"stsz", b"stz2", b"stco", b"co64", b"stss"):
                tracks[-1].tables[kind] = view[a:b]
    except (struct.error, IndexError) as e:
        raise ValueError("a box is cut short") from e
    return tracks


def feature(track: Track) -> str:
    offsets, sizes = track.samples()
    keys = track.keys()
    ranges = ",".join(f"{a}-{b}" for a, b in zip(offsets[keys].tolist(), (offsets + sizes)[keys].tolist()))
    return f"codec={track.codec.strip()};scale={track.time_scale};duration={track.duration};samples={len(sizes)};keys={ranges}"


def payload_of(data: bytes, track: Track) -> bytes:
    """The samples, joined; neighbours in the file are copied at once."""
    offsets, sizes = track.samples()
    if not len(sizes):
        return b""
    breaks = np.flatnonzero(offsets[1:] != offsets[:-1] + sizes[:-1]) + 1
    firsts, lasts = np.concatenate(([0], breaks)), np.concatenate((breaks, [len(sizes)])) - 1
    return b"".join(data[a:b] for a, b in zip(offsets[firsts].tolist(), (offsets + sizes)[lasts].tolist()))


def _store(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for a in range(0, batch.num_rows, 200):
            some = batch.slice(a, 200)
            texts = [(x or "").encode() for x in some.column(1).to_pylist()]
            media = [build(padded(x)) for x in texts]
            yield pa.RecordBatch.from_arrays([some.column(0), pa.array([len(x) for x in texts], pa.int64()), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])


def _read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    sha = lambda x: hashlib.sha256(x).hexdigest()
    names = [c.split()[0] for c in FEATURES_SCHEMA.split(", ")]
    for batch in batches:
        rows = []
        for doc_id, n, media in zip(*(c.to_pylist() for c in batch.columns)):
            (track,) = describe(media)
            payload = payload_of(media, track)
            rows.append((doc_id, n, len(payload), sha(payload), zlib.crc32(payload[-BLOCK:]), len(media), sha(media), feature(track)))
        kinds = [pa.string() if "sha" in c or c == "feature" else pa.int64() for c in names]
        yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=names)


def store_texts(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes and media (the container) of each document, written and read back."""
    rows = docs.selectExpr("cast(doc_id as long) as doc_id", "text").mapInArrow(_store, "doc_id long, n_bytes long, media binary")
    return materialize(rows, "media")


def media_features(stored: DataFrame) -> DataFrame:
    """Digests and features, computed from the stored bytes."""
    return stored.select("doc_id", "n_bytes", "media").mapInArrow(_read, FEATURES_SCHEMA)


TRACK_SCHEMA = "handler string, codec string, seconds double, samples long, key_ranges array<struct<start:long,stop:long>>"


def _columns_of(track: Track) -> dict:
    offsets, sizes = track.samples()
    keys = track.keys()
    return {
        "handler": track.handler, "codec": track.codec, "seconds": track.duration / track.time_scale if track.time_scale else None, "samples": len(sizes),
        "key_ranges": [{"start": a, "stop": b} for a, b in zip(offsets[keys].tolist(), (offsets + sizes)[keys].tolist())],
    }


def _describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    spans = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))
    kinds = {"handler": pa.string(), "codec": pa.string(), "seconds": pa.float64(), "samples": pa.int64(), "key_ranges": spans}
    for batch in batches:
        rows: list[list[dict]] = []
        errors: list[str | None] = []
        for media in batch.column(1).to_pylist():
            try:
                rows.append([_columns_of(track) for track in describe(media or b"")])
                errors.append(None)
            except (ValueError, KeyError, IndexError, struct.error) as e:
                rows.append([])
                errors.append(str(e) or type(e).__name__)
        main = [next((t for t in tracks if t["handler"] == "vide"), tracks[0] if tracks else {}) for tracks in rows]
        columns = {c: pa.array([t.get(c) for t in main], k) for c, k in kinds.items() if c != "handler"}
        tracks = pa.array(rows, pa.list_(pa.struct(list(kinds.items()))))
        yield pa.RecordBatch.from_arrays([batch.column(0), *columns.values(), pa.array(errors, pa.string()), tracks], names=["media_id", *columns, "error", "tracks"])


def media_columns(df: DataFrame, id_col: str, media_col: str) -> DataFrame:
    """Codec, seconds, samples and key-frame byte ranges of a container's first video track (without one: its first track), error, and all its tracks."""
    inner = TRACK_SCHEMA.replace("handler string, ", "")
    schema = f"media_id long, {inner}, error string, tracks array<struct<{TRACK_SCHEMA.replace(' ', ':').replace(',:', ',')}>>"
    return df.selectExpr(f"cast(`{id_col}` as long) as media_id", f"cast(`{media_col}` as binary) as media").mapInArrow(_describe, schema)
