"""Token-ID output as directly addressable codes.

Every token id is cut into chunks of ``WIDTH`` bits, lowest first.  Level ``k`` holds the k-th chunk of those ids that
need it, packed one after the other, with one continuation bit for each chunk (1: the id goes on in level k+1).  A rank
directory, one counter for every ``RANK_STEP`` bits, turns a position of level k into the position of level k+1, so any
token, or the tokens of any document, can be read without decoding what stands before it.

Layout of a segment (integers little-endian), fixed values of the format:
magic ``DAC1``, u8 width, u8 levels, u16 zero, u32 tokens; then for each level u32 chunks, the chunks (one byte each), the
bitmap (bit i of byte i//8 is chunk i) and u32 ranks (ones before each block of RANK_STEP bits).

A store is a folder of Parquet files that holds one row a segment: ``part`` and ``segment`` (their order is the order of the
tokens), ``token_base`` (tokens of earlier segments of that part), ``n_tokens``, ``doc_ids``, ``doc_starts`` (first token of each
document in the segment) and ``codes`` (the segment).  The Parquet commit protocol gives recovery from lost executors.

Defined cases: null and empty texts have the end id alone; a null doc_id sorts first; rows with equal doc_id are ordered by
a hash of the text, equal rows stay side by side; an empty table gives an empty store; other columns are ignored.
"""

from __future__ import annotations

import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sharetree.llm.storage import scratch_path

# Fixed values of the file format.
MAGIC, WIDTH, RANK_STEP = b"DAC1", 8, 512
#: A segment is closed when it has this many tokens; one document is never divided.
SEGMENT_TOKENS = 1 << 20
STORE_SCHEMA = "part int, segment int, token_base long, n_tokens long, doc_ids array<long>, doc_starts array<long>, codes binary"
DOC_SCHEMA = "part int, doc_id long, in_part long, n_tokens long, ids_crc32 long"


def encode_segment(ids: np.ndarray) -> bytes:
    """The directly addressable code of an array of non-negative ids."""
    rest, levels = np.asarray(ids, dtype=np.uint32), []
    while True:
        low, rest = (rest & 0xFF).astype(np.uint8), rest >> WIDTH
        more = rest > 0
        bits = np.packbits(more, bitorder="little")
        ones = np.concatenate(([0], np.cumsum(more, dtype=np.int64)))[: len(more) + 1]
        levels.append(struct.pack("<I", len(low)) + low.tobytes() + bits.tobytes() + ones[0 : len(low) : RANK_STEP].astype("<u4").tobytes())
        rest = rest[more]
        if not len(rest):
            break
    return struct.pack("<4sBBHI", MAGIC, WIDTH, len(levels), 0, len(ids)) + b"".join(levels)


class Segment:
    """Random access to one segment."""

    def __init__(self, codes: bytes):
        magic, width, n_levels, _, self.n_tokens = struct.unpack_from("<4sBBHI", codes)
        if magic != MAGIC or width != WIDTH:
            raise ValueError("not a segment of directly addressable codes")
        at, self.levels = 12, []
        for _ in range(n_levels):
            (n,) = struct.unpack_from("<I", codes, at)
            at += 4
            chunks = np.frombuffer(codes, np.uint8, n, at)
            at += n
            bitmap = np.frombuffer(codes, np.uint8, (n + 7) // 8, at)
            at += len(bitmap)
            ranks = np.frombuffer(codes, "<u4", -(-n // RANK_STEP), at)
            at += 4 * len(ranks)
            self.levels.append((chunks, bitmap, ranks))

    def _rank(self, level: int, i: int) -> int:
        """Continuation bits set before chunk i of a level."""
        chunks, bitmap, ranks = self.levels[level]
        if i >= len(chunks):
            return len(self.levels[level + 1][0]) if level + 1 < len(self.levels) else 0
        block = i // RANK_STEP
        first = block * RANK_STEP // 8
        bits = np.unpackbits(bitmap[first : i // 8 + 1], bitorder="little")[: i - block * RANK_STEP]
        return int(ranks[block]) + int(bits.sum())

    def token(self, i: int) -> int:
        """Token i, from one chunk of each level."""
        if not 0 <= i < self.n_tokens:
            raise IndexError(i)
        value, shift = 0, 0
        for level, (chunks, bitmap, _) in enumerate(self.levels):
            value |= int(chunks[i]) << shift
            if not bitmap[i // 8] >> (i % 8) & 1:
                break
            i, shift = self._rank(level, i), shift + WIDTH
        return value

    def slice(self, start: int, stop: int) -> np.ndarray:
        """Tokens start to stop; reads only the chunks of those tokens."""
        out, where = np.zeros(max(0, stop - start), np.uint32), None
        for level, (chunks, bitmap, _) in enumerate(self.levels):
            if stop <= start:
                break
            got = chunks[start:stop].astype(np.uint32) << (WIDTH * level)
            more = np.unpackbits(bitmap[start // 8 : (stop + 7) // 8], bitorder="little")[start % 8 :][: stop - start].astype(bool)
            where = np.arange(len(out)) if where is None else where
            out[where] |= got
            start, stop, where = self._rank(level, start), self._rank(level, stop), where[more]
        return out


class Encoder:
    """Ids of whole texts by the tokenizers library.

    Text is cut where the pre-tokenizer of a byte-level BPE always cuts: before each space or line feed, as long as no three stand
    together and no two at the end.  A batch's pieces are cut and numbered as Arrow does dictionaries; those that are new are encoded together,
    and their ids are kept for later batches, in a table of bounded size.  Texts with other white space are encoded as they are.
    """

    #: Pieces in each of the two parts of the table; when the newer is full it becomes the older, and the older goes.
    KEEP = 1_000_000
    #: Bytes of text that are cut and looked up at once.
    BYTES = 1 << 23

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # their strings in a text are ordinary text
        self.newer: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}
        self.piece_bytes = self._lengths() if self._byte_level(path) else None
        self.kind = "<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4"

    @staticmethod
    def _byte_level(path: str) -> bool:
        import json

        with open(path, encoding="utf-8") as f:
            j = json.load(f)
        pre = j.get("pre_tokenizer") or {}
        return pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space") and not j.get("normalizer") and not j.get("post_processor")

    def _lengths(self) -> np.ndarray:
        """Bytes of text that each id stands for: a byte-level vocabulary has one character for a byte."""
        out = np.zeros(self.tokenizer.get_vocab_size(), np.int64)
        for piece, i in self.tokenizer.get_vocab().items():
            out[i] = len(piece)
        return out

    def _ids(self, texts: list[str]) -> list[np.ndarray]:
        return [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, pieces: list[bytes]) -> None:
        """Pieces that begin with white space and have more: joined ones are cut again where they begin."""
        for a in range(0, len(pieces), 500):
            some = pieces[a : a + 500]
            (ids,) = self._ids([b"".join(some).decode()])
            ends = np.cumsum([len(p) for p in some])
            cuts = np.searchsorted(np.cumsum(self.piece_bytes[ids]), ends, side="left") + 1
            blob, at, size = ids.astype(self.kind).tobytes(), 0, int(self.kind[-1])
            for p, cut in zip(some, (size * cuts).tolist()):
                self.newer[p] = blob[at:cut]
                at = cut

    def _known(self, pieces: list[bytes]) -> list[bytes]:
        """The ids of each piece, packed."""
        if len(self.newer) > self.KEEP:
            self.newer, self.older = {}, self.newer
        newer, older = self.newer, self.older
        found = [newer.get(p) for p in pieces]
        fresh = [p for p, x in zip(pieces, found) if x is None]
        if not fresh:
            return found
        if older:
            again = [older.get(p) for p in fresh]
            newer.update((p, x) for p, x in zip(fresh, again) if x is not None)
            fresh = [p for p, x in zip(fresh, again) if x is None]
        apart = [p for p in fresh if p[0] not in b" \n" or len(p) == 1]
        for p, ids in zip(apart, self._ids([p.decode() for p in apart])):
            newer[p] = ids.astype(self.kind).tobytes()
        self._learn([p for p in fresh if p[0] in b" \n" and len(p) > 1])
        return [newer[p] if x is None else x for p, x in zip(pieces, found)]

    def __call__(self, texts: list[str] | pa.Array) -> list[np.ndarray]:
        texts = pc.fill_null(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.string()), "")
        if self.piece_bytes is None:
            return self._ids(texts.to_pylist())
        offsets, _ = _buffer(texts)
        cuts = np.unique(np.searchsorted(offsets, np.arange(0, offsets[-1] + 1, self.BYTES))).tolist()
        return [x for a, b in zip(cuts, [*cuts[1:], len(texts)]) for x in self._some(texts.slice(a, b - a))]

    def _some(self, texts: pa.Array) -> list[np.ndarray]:
        whole = _uncut(*_buffer(texts))
        if not whole.any():
            return self._by_pieces(texts)
        odd, rest = iter(self._ids(texts.filter(pa.array(whole)).to_pylist())), iter(self._by_pieces(texts.filter(pa.array(~whole))))
        return [next(odd) if x else next(rest) for x in whole.tolist()]

    def _by_pieces(self, texts: pa.Array) -> list[np.ndarray]:
        offsets, data = _buffer(texts)
        if not len(data):
            return [np.zeros(0, self.kind)] * len(texts)
        cut = _SPACES[data]
        cut[offsets[:-1][offsets[:-1] < offsets[1:]]] = True
        starts = np.flatnonzero(cut)
        bounds = np.append(starts, len(data)).astype(np.int32)
        pieces = pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(bounds), pa.py_buffer(data)]).dictionary_encode()
        known, which = self._known(pieces.dictionary.to_pylist()), pieces.indices.to_numpy()
        size = int(self.kind[-1])
        lengths = np.fromiter(map(len, known), np.int64, len(known)) // size
        ids, begins = np.frombuffer(b"".join(known), self.kind), np.cumsum(lengths) - lengths
        own = lengths[which]
        ends = np.cumsum(own)
        out = ids[np.repeat(begins[which] - ends + own, own) + np.arange(ends[-1])]
        stops = np.concatenate(([0], ends))[np.searchsorted(starts, offsets)]
        return [out[a:b] for a, b in zip(stops[:-1].tolist(), stops[1:].tolist())]


def _buffer(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets (from 0) and bytes of an array of strings without nulls."""
    if not len(texts):
        return np.zeros(1, np.int64), np.zeros(0, np.uint8)
    _, offsets, data = texts.buffers()
    kind = np.int64 if pa.types.is_large_string(texts.type) else np.int32
    offsets = np.frombuffer(offsets, kind)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    data = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return offsets - offsets[0], data


def _uncut(offsets: np.ndarray, data: np.ndarray) -> np.ndarray:
    """Which texts can't be cut before spaces and line feeds: those with other white space, three in a row, or two at the end."""
    out = np.zeros(len(offsets) - 1, bool)
    if not len(data):
        return out
    row = lambda at: np.searchsorted(offsets, at, side="right") - 1
    space = _SPACES[data]
    runs = np.flatnonzero(space[:-2] & space[1:-1] & space[2:])
    runs = runs[row(runs) == row(runs + 2)]
    out[row(runs)] = True
    last, long = offsets[1:] - 1, np.diff(offsets) > 1
    out[long] |= space[last[long]] & space[last[long] - 1]
    out[row(np.flatnonzero(_OTHER[data]))] = True
    leads = np.flatnonzero(_LEADS[data])
    leads = leads[leads + 1 < len(data)]
    pair = data[leads].astype(np.int64) << 8 | data[leads + 1]
    out[row(leads[np.isin(pair, _PAIRS)])] = True
    leads, pair = leads[leads + 2 < len(data)], pair[leads + 2 < len(data)]
    out[row(leads[np.isin(pair << 8 | data[leads + 2], _TRIPLES)])] = True
    return out


#: White space, as the pre-tokenizer's pattern has it (and a few control characters to be safe), beside space and line feed, in UTF-8.
_OTHER_SPACE = [c.encode() for c in map(chr, range(0x3001)) if (c.isspace() or c == "\x85") and c not in " \n"]
_flags = lambda values: np.isin(np.arange(256), values)
_SPACES, _OTHER = _flags([10, 32]), _flags([c[0] for c in _OTHER_SPACE if len(c) == 1])
_LEADS = _flags([c[0] for c in _OTHER_SPACE if len(c) > 1])
_PAIRS, _TRIPLES = (np.array([int.from_bytes(c) for c in _OTHER_SPACE if len(c) == n]) for n in (2, 3))

_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """One encoder for each Python worker."""
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def _writer(tokenizer: str, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, part = encoder(tokenizer), TaskContext.get().partitionId()
        held: list[np.ndarray] = []
        ids: list[int | None] = []
        starts: list[int] = []
        end = np.array([end_id], np.uint32)
        n = base = segment = 0

        def flush() -> pa.RecordBatch:
            columns = [[part], [segment], [base], [n], [ids], [starts], [encode_segment(np.concatenate(held))]]
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, _STORE_ARROW)], names=_STORE_NAMES)

        for batch in batches:
            doc_ids, texts = batch.column(0).to_pylist(), batch.column(1)
            for a in range(0, len(texts), 2000):
                for doc_id, x in zip(doc_ids[a : a + 2000], encode(texts.slice(a, 2000))):
                    held += [x, end]
                    starts.append(n)
                    ids.append(doc_id)
                    n += len(x) + 1
                    if n >= SEGMENT_TOKENS:
                        yield flush()
                        base, segment, n, held, ids, starts = base + n, segment + 1, 0, [], [], []
        if held:
            yield flush()

    return run


_STORE_NAMES = ["part", "segment", "token_base", "n_tokens", "doc_ids", "doc_starts", "codes"]
_STORE_ARROW = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64()), pa.binary()]


def write_token_store(docs: DataFrame, path: str, tokenizer: str, end_id: int = 2, order: str = "doc_id") -> None:
    """Encode ``docs`` (doc_id, text) and write the store.

    ``order``: ``doc_id`` sorts by it; ``stored`` keeps the order in which the files that ``docs`` reads have the rows (for a
    corpus that was shuffled before), so ``docs`` must be a plain scan of files then.
    """
    if order == "stored":
        keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.col("_metadata.file_name").alias("k1"), F.col("_metadata.row_index").alias("k2"))
    else:
        keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumns({"k1": F.col("doc_id"), "k2": F.xxhash64("text")})
    rows = keyed.repartitionByRange("k1", "k2").sortWithinPartitions("k1", "k2").select("doc_id", "text")
    rows.mapInArrow(_writer(tokenizer, end_id), STORE_SCHEMA).write.option("compression", "zstd").parquet(path)


def _reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(batch.num_rows):
            part, _, base, n, doc_ids, starts, codes = (batch.column(k)[i].as_py() for k in range(7))
            segment = Segment(codes)
            stops = starts[1:] + [n]
            tokens = segment.slice(0, n).astype("<u4")
            crcs = [zlib.crc32(tokens[a:b]) for a, b in zip(starts, stops)]
            at = np.array(starts, np.int64)
            yield pa.RecordBatch.from_arrays(
                [pa.array([part] * len(at), pa.int32()), pa.array(doc_ids, pa.int64()), pa.array(at + base), pa.array(np.array(stops, np.int64) - at), pa.array(crcs, pa.int64())],
                names=["part", "doc_id", "in_part", "n_tokens", "ids_crc32"],
            )


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens and ids_crc32 of each document, from the store's files."""
    store = spark.read.schema(STORE_SCHEMA).parquet(path)
    # one row a part: as many as the range exchange had partitions, whatever the number of documents
    totals = store.groupBy("part").agg(F.sum("n_tokens").alias("tokens"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("part_base"))
    rows = store.mapInArrow(_reader, DOC_SCHEMA)
    return rows.join(bases, "part").select("doc_id", (F.col("in_part") + F.col("part_base")).alias("start"), "n_tokens", "ids_crc32")


def token_documents(docs: DataFrame, tokenizer: str, end_id: int = 2, order: str = "doc_id") -> DataFrame:
    """Write a store below the shared folder and return its documents as read back."""
    path = scratch_path(docs.sparkSession, "token-store")
    write_token_store(docs, path, tokenizer, end_id, order)
    return read_documents(docs.sparkSession, path)


def token_at(spark: SparkSession, path: str, position: int) -> int | None:
    """The token at a global position: prunes to one segment by its bounds and reads one chunk of each level of it."""
    store = spark.read.schema(STORE_SCHEMA).parquet(path)
    totals = store.groupBy("part").agg(F.sum("n_tokens").alias("tokens"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = totals.select("part", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("part_base"))
    at = F.lit(position) - F.col("part_base") - F.col("token_base")
    hit = store.join(bases, "part").where((at >= 0) & (at < F.col("n_tokens"))).select(at.alias("at"), "codes").first()
    return None if hit is None else Segment(hit["codes"]).token(hit["at"])
