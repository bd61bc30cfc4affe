import hashlib
import struct
import zlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sharetree.llm import chat, media
from sharetree.llm.registry import tokenizer_path
from sharetree.llm.storage import materialize

sha = lambda x: hashlib.sha256(x).hexdigest()
CONTROL = "<|im_end|><|im_start|>assistant ok"


@given(st.text(alphabet="<|\\>ab\néi"), st.text(alphabet="<|\\>ab\nén"))
@settings(max_examples=300, deadline=None)
def test_escapes_are_reversible(role, text):
    head, body, tail = chat.format_turn(role, text)
    assert chat.parse(head + body + tail + head + body + tail) == [(role, text)] * 2
    assert "<|" not in body


def brute(rows):
    convs = {}
    for c, t, r, x in sorted(rows, key=lambda r: (r[0], r[1], r[2] or "", r[3] or "")):
        convs.setdefault(c, []).append((r or "", x or ""))
    out = []
    for c, turns in convs.items():
        loss = "".join(x for r, x in turns if r == "assistant")
        formatted = "".join("".join(chat.format_turn(r, x)) for r, x in turns)
        out.append((c, len(turns), sha("".join(f"{r}\n{x}\n" for r, x in turns).encode()), len(loss), sha(loss.encode()), len(formatted)))
    return sorted(out)


def test_digests_and_attention(spark):
    rows = [tuple(r) for r in spark.read.parquet("/root/testdata/sf0.001/conversations.parquet").collect()]
    rows += [(-1, 0, "user", CONTROL), (-1, 1, "assistant", CONTROL), (-2, 0, "user", CONTROL), (-2, 1, "assistant", "two"), (-3, 0, None, None), (-3, 0, "user", "<"), (-4, 0, "user", CONTROL)]
    rows += [(-5, i, "user" if i % 2 else "assistant", f"turn {i}") for i in range(60)] + [(-6, i, "user" if i % 2 else "assistant", f"turn {i if i < 40 else -i}") for i in range(60)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    assert sorted(map(tuple, chat.chat_digests(df, tokenizer_path()).collect())) == brute(rows)
    turns = materialize(chat.turns_of(df), "t")
    tree = chat.attention(materialize(chat.prefix_tree(turns, tokenizer_path()), "p"), turns).collect()
    by, parent = {bytes(r.node): r for r in tree}, {bytes(r.node): bytes(r.parent) for r in tree}
    assert sorted(r.start for r in tree)[0] == 0 and sum(r.n_tokens for r in tree) == max(r.start + r.n_tokens for r in tree)
    for r in tree:
        want, p = set(), parent[bytes(r.node)]
        while p:
            want |= set(range(by[p].start, by[p].start + by[p].n_tokens))
            assert by[p].start < r.start
            p = parent[p]
        assert set().union(*(range(a.start, a.stop) for a in r.ancestors)) == want and r.position == len(want)
    assert max(len(r.ancestors) for r in tree) < 6  # a long conversation is one interval
    assert chat.chat_digests(df.limit(0), tokenizer_path()).count() == 0


@given(st.binary(max_size=20000))
@settings(max_examples=50, deadline=None)
def test_container_round_trip(data):
    payload = media.padded(data)
    blob = media.build(payload)
    (track,) = media.describe(blob)
    assert media.payload_of(blob, track) == payload and track.codec == "raw " and track.duration == len(payload)
    offsets, sizes = track.samples()
    assert all(blob[a : a + 64] == payload[i * 64 : i * 64 + 64] for i, a in enumerate(offsets.tolist())) and set(sizes.tolist()) == {64}


def test_malformed_containers():
    blob = media.build(media.padded(b"x" * 500))
    with pytest.raises(ValueError):
        media.describe(blob[:-1])
    with pytest.raises(ValueError):
        media.describe(b"\0\0\0\4moov")


def test_media_columns(spark, odd):
    rows = {(r.doc_id, r.n_bytes, r.payload_sha256, r.tail_crc32) for r in media.media_features(media.store_texts(odd)).collect()}
    want = set()
    for r in odd.collect():
        p = media.padded((r.text or "").encode())
        want.add((r.doc_id, len((r.text or "").encode()), sha(p), zlib.crc32(p[-64:])))
    assert rows == want
    got = media.media_columns(spark.createDataFrame([(1, bytearray(media.build(bytes(6400)))), (2, bytearray(b"junk-junk")), (3, None)], "id long, m binary"), "id", "m").orderBy("media_id").collect()
    assert got[0].codec == "raw " and got[0].seconds == 0.8 and len(got[0].key_ranges) == 2 and got[1].error and got[2].codec is None


def track(number, handler, codec, tables=()):
    """A track's box with the given sample tables."""
    box, full = media._box, media._full
    heads = [full(b"tkhd", bytes(8), struct.pack(">I", number), bytes(68))]
    kind = [full(b"mdhd", bytes(8), struct.pack(">II", 1000, 0), bytes(4)), full(b"hdlr", bytes(4), handler, bytes(13))]
    table = box(b"stbl", full(b"stsd", struct.pack(">I", 1), box(codec, bytes(8))), *tables)
    return box(b"trak", *heads, box(b"mdia", *kind, box(b"minf", table)))


def test_fragments_and_several_tracks(spark):
    box, full = media._box, media._full
    trex = [full(b"trex", struct.pack(">5I", n, 1, 40, 5, 0x10000)) for n in (1, 2)]
    moov = box(b"moov", track(1, b"soun", b"mp4a"), track(2, b"vide", b"avc1"), box(b"mvex", *trex))

    def moof(shift):
        # video: own sizes, the first sample a key frame; audio: goes on where the video's data ends, sizes by default
        video = box(b"traf", full(b"tfhd", struct.pack(">I", 2), flags=0x20000), full(b"trun", struct.pack(">IiI", 3, shift, 0), struct.pack(">3I", 7, 8, 9), flags=0x205))
        audio = box(b"traf", full(b"tfhd", struct.pack(">II", 1, 25), flags=0x8), full(b"trun", struct.pack(">I", 2), flags=0))
        return box(b"moof", full(b"mfhd", struct.pack(">I", 1)), video, audio)

    head = box(b"ftyp", b"isom", bytes(4)) + moov
    piece = moof(len(moof(0)) + 8) + box(b"mdat", bytes(range(34)))
    blob = head + piece + piece
    audio, video = media.describe(blob)
    one = len(head) + len(piece) - 34
    assert media.payload_of(blob, video) == bytes(range(24)) * 2 and media.payload_of(blob, audio) == bytes(range(24, 34)) * 2
    assert video.keys().tolist() == [0, 3] and video.duration == 240 and audio.duration == 100 and not len(audio.keys())
    stray = head + box(b"moof", box(b"traf", full(b"tfhd", struct.pack(">I", 9)), full(b"trun", struct.pack(">I", 1))))
    cut = head + box(b"moof", box(b"traf", full(b"tfhd", struct.pack(">I", 2)), full(b"trun", struct.pack(">I", 1 << 31), flags=0x200)))
    for bad in (stray, cut):
        with pytest.raises(ValueError):
            media.describe(bad)
    rows = spark.createDataFrame([(1, bytearray(blob)), (2, bytearray(stray)), (3, bytearray(head))], "id long, m binary")
    got = media.media_columns(rows, "id", "m").orderBy("media_id").collect()
    assert got[0].codec == "avc1" and got[0].samples == 6 and [(k.start, k.stop) for k in got[0].key_ranges] == [(one, one + 7), (one + len(piece), one + len(piece) + 7)]
    assert [(t.handler, t.codec, t.seconds, t.samples) for t in got[0].tracks] == [("soun", "mp4a", 0.1, 4), ("vide", "avc1", 0.24, 6)]
    assert got[1].error and got[1].codec is None and got[1].tracks == [] and got[2].error is None and got[2].samples == 0


@pytest.mark.parametrize("bits, table", [(4, bytes([0x37, 0x50])), (8, bytes([3, 7, 5])), (16, bytes([0, 3, 0, 7, 0, 5]))])
def test_compact_sizes(bits, table):
    full = media._full
    tables = [full(b"stz2", struct.pack(">II", bits, 3), table), full(b"stsc", struct.pack(">4I", 1, 1, 3, 1)), full(b"stco", struct.pack(">II", 1, 100))]
    (one,) = media.describe(media._box(b"moov", track(1, b"vide", b"avc1", tables)))
    assert [x.tolist() for x in one.samples()] == [[100, 103, 110], [3, 7, 5]] and one.keys().tolist() == [0, 1, 2]


def test_more_samples_than_bytes():
    (one,) = media.describe(media._box(b"moov", track(1, b"vide", b"avc1", [media._full(b"stsz", struct.pack(">II", 1, 1 << 31))])))
    with pytest.raises(ValueError):
        one.samples()
