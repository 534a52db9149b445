import struct
import zlib

from vpatterns.llm import media


def test_round_trip():
    for n in (64, 128, 4096, 4096 * 3 + 64, 64 * 65):
        raw = bytes(i * 7 % 251 for i in range(n))
        data = media.store(raw)
        payload, feature = media.read_back(data)
        assert payload == raw and f"duration={n};samples={n // 64}" in feature


def test_ragged_last_sample():
    raw = b"x" * 100
    assert media.read_back(media.store(raw))[0] == raw


def test_tables_name_the_keyframes():
    t = media.tracks(media.store(b"\1" * 64 * 40))[0]
    assert (t.codec, t.timescale, t.handler, t.keyframes()) == ("raw ", 8000, "soun", [0, 16, 32])
    assert all(size == 64 for _, size in t.ranges())


def test_fragments():
    box = media._box
    moov = box(b"moov", box(b"trak", box(b"tkhd", struct.pack(">IIII", 0, 0, 0, 5)), box(b"mdia", box(b"mdhd", struct.pack(">IIII", 0, 0, 0, 1000) + bytes(8)), box(b"minf", box(b"stbl", box(b"stsd", struct.pack(">II", 0, 1), box(b"avc1", bytes(70))))))), box(b"mvex", box(b"trex", struct.pack(">6I", 0, 5, 1, 40, 0, 0x10000))))
    run = box(b"trun", struct.pack(">IIiI", 0x205, 2, 500, 0), struct.pack(">II", 7, 9))
    frag = box(b"moof", box(b"traf", box(b"tfhd", struct.pack(">II", 0, 5)), run))
    t = media.tracks(moov + frag)[0]
    base = len(moov)
    assert t.codec == "avc1" and t.runs == [(base + 500, 7, True), (base + 507, 9, False)] and t.length() == 80


def test_inspect_and_broken_containers(spark):
    df = spark.createDataFrame([(1, media.store(b"a" * 64)), (2, b"no container"), (3, None), (4, media.store(b"a" * 64)[:50])], "doc_id long, data binary")
    got = media.inspect(df, "doc_id", "data").collect()
    assert [(r["doc_id"], r["codec"], r["n_samples"], r["duration"]) for r in got] == [(1, "raw ", 1, 64)]


def test_query_columns(make):
    got = {r["doc_id"]: r for r in media.stored(make(["héllo", "héllo", None])).collect()}
    pad = "héllo".encode().ljust(64, b"\0")
    assert got[0]["tail_crc32"] == zlib.crc32(pad) and got[0]["media_sha256"] == got[1]["media_sha256"]
    assert (got[0]["n_bytes"], got[2]["n_bytes"], got[2]["payload_bytes"]) == (6, 0, 64)
