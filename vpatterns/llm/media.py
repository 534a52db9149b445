"""ISO media containers: boxes, sample tables and keyframe ranges without decoding.

``inspect`` walks the nested boxes of any container held in a binary column and
gives one row per track: codec, timescale, duration, samples and the byte ranges of
its keyframes, all from the sample tables (sizes, chunk map, chunk offsets, times,
sync samples) or, in fragmented files, from the track runs. ``store`` is the writer
that puts bytes losslessly into such a container as 8-bit samples.

Defined cases: a null text is the empty text, stored as 64 zero bytes; equal texts
give equal bytes; a null or broken container gives no track rows; other columns are
not read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from vpatterns.llm.common import documents

#: Fixed values of the format: boxes that hold boxes, with the bytes before the first child.
NESTED = {b"moov": 0, b"trak": 0, b"mdia": 0, b"minf": 0, b"stbl": 0, b"edts": 0, b"dinf": 0, b"mvex": 0, b"moof": 0, b"traf": 0, b"udta": 0, b"meta": 4}
PAD = 64
#: Bytes of one stored sample, samples of one chunk, and samples from one keyframe to the next.
SAMPLE, PER_CHUNK, KEY_EVERY = 64, 64, 16
RATE = 8000


def boxes(data, start: int = 0, stop: int | None = None):
    """(kind, path, first byte of the body, end) of every box, parents before children."""
    stack = [(start, len(data) if stop is None else stop, b"")]
    while stack:
        at, end, path = stack.pop()
        if at + 8 > end:
            continue
        size, kind = struct.unpack_from(">I4s", data, at)
        head = 8
        if size == 1:
            if at + 16 > end:
                continue
            size, head = struct.unpack_from(">Q", data, at + 8)[0], 16
        elif size == 0:
            size = end - at
        if size < head or at + size > end:
            continue
        stack.append((at + size, end, path))
        name = path + b"/" + kind
        yield kind, name, at + head, at + size
        if kind in NESTED:
            stack.append((at + head + NESTED[kind], at + size, name))


def _u32s(data, at: int, n: int) -> tuple[int, ...]:
    return struct.unpack_from(f">{n}I", data, at)


class Track:
    def __init__(self):
        self.id, self.codec, self.timescale, self.duration, self.handler = 0, "", 0, 0, ""
        self.sizes: list[int] = []
        self.offsets: list[int] = []
        self.map: list[tuple[int, int]] = []
        self.times: list[tuple[int, int]] = []
        self.keys: set[int] | None = None
        self.runs: list[tuple[int, int, bool]] = []
        self.run_time = 0

    def ranges(self) -> list[tuple[int, int]]:
        """(first byte, length) of each sample of the tables, then of the fragments."""
        out, sample = [], 0
        steps = {first: n for first, n in self.map}
        per = 0
        for chunk, at in enumerate(self.offsets, 1):
            per = steps.get(chunk, per)
            for size in self.sizes[sample : sample + per]:
                out.append((at, size))
                at += size
            sample += per
        return out + [(at, size) for at, size, _ in self.runs]

    def keyframes(self) -> list[int]:
        n = min(len(self.sizes), len(self.ranges()) - len(self.runs))
        table = list(range(n)) if self.keys is None else sorted(k - 1 for k in self.keys if k <= n)
        return table + [n + i for i, r in enumerate(self.runs) if r[2]]

    def length(self) -> int:
        return max(self.duration, sum(n * d for n, d in self.times), self.run_time)


def tracks(data: bytes) -> list[Track]:
    found: list[Track] = []
    by_id: dict[int, Track] = {}
    moof, frag, base, flags0 = 0, None, 0, (0, 0, 0)
    defaults: dict[int, tuple[int, int, int]] = {}
    for kind, path, at, end in boxes(data):
        if kind == b"trak":
            found.append(Track())
            continue
        if kind == b"moof":
            moof = at - 8
            continue
        if kind == b"trex":
            _, track, _, *rest = _u32s(data, at, 6)
            defaults[track] = tuple(rest)
            continue
        if kind == b"tfhd":
            bits, track = _u32s(data, at, 2)
            frag, base, pos = by_id.get(track), moof, at + 8
            duration, size, flags = defaults.get(track, (0, 0, 0))
            if bits & 1:
                base, pos = struct.unpack_from(">Q", data, pos)[0], pos + 8
            pos += 4 * bool(bits & 2)
            if bits & 8:
                duration, pos = _u32s(data, pos, 1)[0], pos + 4
            if bits & 16:
                size, pos = _u32s(data, pos, 1)[0], pos + 4
            if bits & 32:
                flags = _u32s(data, pos, 1)[0]
            flags0 = (duration, size, flags)
            continue
        if kind == b"trun" and frag is not None:
            bits, n = _u32s(data, at, 2)
            pos, where, first = at + 8, base, None
            if bits & 1:
                where, pos = base + struct.unpack_from(">i", data, pos)[0], pos + 4
            if bits & 4:
                first, pos = _u32s(data, pos, 1)[0], pos + 4
            for i in range(n):
                duration, size, flags = flags0
                if bits & 0x100:
                    duration, pos = _u32s(data, pos, 1)[0], pos + 4
                if bits & 0x200:
                    size, pos = _u32s(data, pos, 1)[0], pos + 4
                if bits & 0x400:
                    flags, pos = _u32s(data, pos, 1)[0], pos + 4
                pos += 4 * bool(bits & 0x800)
                flags = first if first is not None and not i else flags
                frag.runs.append((where, size, not flags & 0x10000))
                frag.run_time += duration
                where += size
            continue
        if not found or b"/trak" not in path:
            continue
        t = found[-1]
        if kind == b"tkhd":
            t.id = _u32s(data, at + (20 if data[at] else 12), 1)[0]
            by_id[t.id] = t
        elif kind == b"mdhd":
            t.timescale, t.duration = struct.unpack_from(">IQ" if data[at] else ">II", data, at + (20 if data[at] else 12))
        elif kind == b"hdlr":
            t.handler = bytes(data[at + 8 : at + 12]).decode("latin-1")
        elif kind == b"stsd" and end - at >= 16:
            t.codec = bytes(data[at + 12 : at + 16]).decode("latin-1")
        elif kind == b"stts":
            n = _u32s(data, at + 4, 1)[0]
            flat = _u32s(data, at + 8, 2 * n)
            t.times = list(zip(flat[::2], flat[1::2]))
        elif kind == b"stsc":
            n = _u32s(data, at + 4, 1)[0]
            flat = _u32s(data, at + 8, 3 * n)
            t.map = list(zip(flat[::3], flat[1::3]))
        elif kind == b"stsz":
            size, n = _u32s(data, at + 4, 2)
            t.sizes = [size] * n if size else list(_u32s(data, at + 12, n))
        elif kind == b"stz2":
            width, n = data[at + 7], _u32s(data, at + 8, 1)[0]
            raw = data[at + 12 : end]
            if width == 4:
                t.sizes = [raw[i // 2] >> 4 if i % 2 == 0 else raw[i // 2] & 15 for i in range(n)]
            else:
                t.sizes = list(struct.unpack_from(f">{n}{'B' if width == 8 else 'H'}", raw))
        elif kind == b"stco":
            t.offsets = list(_u32s(data, at + 8, _u32s(data, at + 4, 1)[0]))
        elif kind == b"co64":
            n = _u32s(data, at + 4, 1)[0]
            t.offsets = list(struct.unpack_from(f">{n}Q", data, at + 8))
        elif kind == b"stss":
            t.keys = set(_u32s(data, at + 8, _u32s(data, at + 4, 1)[0]))
    return found


def _box(kind: bytes, *body: bytes) -> bytes:
    inner = b"".join(body)
    return struct.pack(">I4s", 8 + len(inner), kind) + inner


def store(payload: bytes) -> bytes:
    """A container whose one sound track holds the payload as 8-bit samples.

    The media data box comes first with a 64-bit size, so chunk offsets do not
    depend on the tables' length.
    """
    n = -(-len(payload) // SAMPLE)
    chunks = -(-n // PER_CHUNK)
    brand = _box(b"ftyp", b"isom", bytes(4), b"isom")
    at = len(brand) + 16
    media = struct.pack(">I4sQ", 1, b"mdat", 16 + len(payload)) + payload
    offsets = [at + i * SAMPLE * PER_CHUNK for i in range(chunks)]
    wide = b"co64" if offsets and offsets[-1] >> 32 else b"stco"
    last = len(payload) - (n - 1) * SAMPLE if n else 0
    sizes = struct.pack(">III", 0, SAMPLE, n) if last == SAMPLE else struct.pack(f">III{n}I", 0, 0, n, *[SAMPLE] * (n - 1), last)
    full, tail = chunks - 1, n - (chunks - 1) * PER_CHUNK
    runs = [(1, PER_CHUNK, 1)] * bool(full) + [(chunks, tail, 1)] * (not full or tail != PER_CHUNK)
    keys = range(1, n + 1, KEY_EVERY)
    entry = struct.pack(">6xHIIHHHHI", 1, 0, 0, 1, 8, 0, 0, RATE << 16)
    table = _box(
        b"stbl",
        _box(b"stsd", struct.pack(">II", 0, 1), _box(b"raw ", entry)),
        _box(b"stts", struct.pack(">IIII", 0, 1, n, SAMPLE)),
        _box(b"stsc", struct.pack(">II", 0, len(runs)), *(struct.pack(">III", *r) for r in runs)),
        _box(b"stsz", sizes),
        _box(wide, struct.pack(f">II{chunks}{'Q' if wide == b'co64' else 'I'}", 0, chunks, *offsets)),
        _box(b"stss", struct.pack(f">II{len(keys)}I", 0, len(keys), *keys)),
    )
    head = struct.pack(">IIIII", 0, 0, 0, RATE, len(payload))
    track = _box(
        b"trak",
        _box(b"tkhd", struct.pack(">IIIII", 3, 0, 0, 1, 0), struct.pack(">I", len(payload)), bytes(60)),
        _box(b"mdia", _box(b"mdhd", head, bytes(4)), _box(b"hdlr", bytes(8), b"soun", bytes(13)), _box(b"minf", _box(b"smhd", bytes(8)), table)),
    )
    return brand + media + _box(b"moov", _box(b"mvhd", head, bytes(80)), track)


def read_back(data: bytes) -> tuple[bytes, str]:
    """(payload put together from the first track's samples, feature of its tables)."""
    track = tracks(data)[0]
    ranges, keys = track.ranges(), track.keyframes()
    view, parts, at = memoryview(data), [], 0
    while at < len(ranges):  # neighbours in the file are copied together
        first, end = ranges[at][0], sum(ranges[at])
        at += 1
        while at < len(ranges) and ranges[at][0] == end:
            end += ranges[at][1]
            at += 1
        parts.append(view[first:end])
    spans = [ranges[k] for k in keys]
    digest = zlib.crc32(struct.pack(f">{2 * len(spans)}Q", *(x for s in spans for x in s)))
    kinds = ",".join(kind.decode("latin-1") for kind, path, _, _ in boxes(data) if path.count(b"/") == 1)
    feature = f"{kinds};codec={track.codec.strip()};rate={track.timescale};duration={track.length()};samples={len(ranges)};keyframes={len(keys)};first={spans[0][0]}+{spans[0][1]};last={spans[-1][0]}+{spans[-1][1]};ranges={digest:08x}"
    return b"".join(parts), feature


def inspect(df: DataFrame, id_col: str, data_col: str) -> DataFrame:
    """One row per track of each container; payloads are never decoded."""

    def step(batches):
        for batch in batches:
            rows = []
            for key, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                try:
                    found = tracks(data or b"")
                except (struct.error, IndexError):
                    found = []
                for t in found:
                    ranges = t.ranges()
                    spans = [{"at": ranges[k][0], "length": ranges[k][1]} for k in t.keyframes()]
                    rows.append((key, t.id, t.handler, t.codec, t.timescale, t.length(), len(ranges), spans))
            columns = list(zip(*rows)) or [()] * 8
            kinds = [batch.schema.field(0).type, pa.int64(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("at", pa.int64()), ("length", pa.int64())]))]
            names = [id_col, "track", "handler", "codec", "timescale", "duration", "n_samples", "keyframes"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=names)

    kind = df.schema[id_col].dataType.simpleString()
    return df.select(id_col, data_col).mapInArrow(step, f"`{id_col}` {kind}, track long, handler string, codec string, timescale long, duration long, n_samples long, keyframes array<struct<at: long, length: long>>")


def stored(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", keep_bytes: bool = True) -> DataFrame:
    """Texts put into containers and read back from them; ``media`` holds the container if asked for."""
    names = [id_col, "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]

    def step(batches):
        for batch in batches:
            kinds = [batch.schema.field(0).type, pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            for at in range(0, batch.num_rows, 256):
                rows, blobs = [], []
                for key, text in zip(batch.column(0)[at : at + 256].to_pylist(), batch.column(1)[at : at + 256].to_pylist()):
                    raw = (text or "").encode()
                    data = store(raw.ljust(max(PAD, -(-len(raw) // PAD) * PAD), b"\0"))
                    payload, feature = read_back(data)
                    rows.append((key, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-PAD:]), len(data), hashlib.sha256(data).hexdigest(), feature))
                    blobs.append(data)
                arrays = [pa.array(c, k) for c, k in zip(zip(*rows), kinds)]
                if keep_bytes:
                    arrays.append(pa.array(blobs, pa.binary()))
                yield pa.RecordBatch.from_arrays(arrays, names=names + ["media"] * keep_bytes)

    kind = df.schema[id_col].dataType.simpleString()
    out = f"`{id_col}` {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return df.select(id_col, text_col).mapInArrow(step, out + ", media binary" * keep_bytes)


def op4_iso_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stored(documents(spark, sf_dir), keep_bytes=False)
