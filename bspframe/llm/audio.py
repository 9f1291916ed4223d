"""MPEG audio media columns: writing, resynchronising and measuring MPEG audio streams.

``to_media`` stores a byte payload losslessly in a valid MPEG-1 Layer III stream: silent mono frames at 48 kHz
whose ancillary area carries the payload, each with its CRC-16, behind an ID3v2 tag and a variable-bitrate
(Xing) table; the last frame takes the smallest bitrate that fits. ``parse`` reads any MPEG-1/2/2.5 Layer I-III
stream: it skips and parses ID3v2 (unsynchronised ones too) and ID3v1 tags, finds frame headers again after damage, reads
variable-bitrate tables of both kinds (Xing/Info and VBRI), verifies frame checksums of every layer over the bits that the
layer protects, and gives the exact duration and every frame's offset. Frames of free-format bitrate are skipped.

Defined results: a null text is empty; the payload is the UTF-8 text with zero bytes up to a positive
multiple of 64; equal texts give equal media; null media parses as an empty stream; repeated rows give as many rows; an
empty table gives none; a text of any length is stored whole; columns beyond doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
import zlib
from fractions import Fraction

import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from bspframe.llm import text as K
from bspframe.session import ship

# Fixed values of the MPEG audio format.
#: kbit/s by (MPEG-1?, layer), index 1 to 14
BITRATES = {
    (True, 1): [32, 64, 96, 128, 160, 192, 224, 256, 288, 320, 352, 384, 416, 448],
    (True, 2): [32, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320, 384],
    (True, 3): [32, 40, 48, 56, 64, 80, 96, 112, 128, 160, 192, 224, 256, 320],
    (False, 1): [32, 48, 56, 64, 80, 96, 112, 128, 144, 160, 176, 192, 224, 256],
    (False, 2): [8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160],
    (False, 3): [8, 16, 24, 32, 40, 48, 56, 64, 80, 96, 112, 128, 144, 160],
}
#: Hz by version bits
RATES = {3: [44100, 48000, 32000], 2: [22050, 24000, 16000], 0: [11025, 12000, 8000]}
#: Layer II: bits of each subband's allocation, by (subbands with 4, with 3, with 2 bits)
ALLOCATIONS = {"a": (11, 12, 4), "b": (11, 12, 7), "c": (2, 6, 0), "d": (2, 10, 0), "low": (4, 7, 19)}
SYNC = 0xFFE0

RATE, SIDE, LEAD = 48000, 17, 4 + 2 + 17
SAMPLES = 1152


def _crc_table() -> list[int]:
    out = []
    for byte in range(256):
        c = byte << 8
        for _ in range(8):
            c = (c << 1 ^ 0x8005) & 0xFFFF if c & 0x8000 else c << 1
        out.append(c)
    return out


_CRC = _crc_table()


def crc16(data: bytes) -> int:
    """The checksum of MPEG frames, over the last two header bytes and the side information."""
    c = 0xFFFF
    for b in data:
        c = (c << 8 & 0xFF00) ^ _CRC[c >> 8 ^ b]
    return c


def _lead(index: int) -> bytes:
    """Header, checksum and silent side information of a 48 kHz mono Layer III frame."""
    head = bytes([0xFF, 0xFA, index << 4 | 1 << 2, 0xC0])
    side = bytes(SIDE)
    return head + crc16(head[2:] + side).to_bytes(2, "big") + side


#: (frame bytes, lead) by bitrate, smallest first; 48 kHz frames have whole sizes.
_KINDS = [(kbps * SAMPLES // 8 * 1000 // RATE, _lead(i + 1)) for i, kbps in enumerate(BITRATES[True, 3])]
_FULL, _FULL_LEAD = _KINDS[-1]
ROOM = _FULL - LEAD


def _safe(n: int) -> bytes:
    return bytes(n >> s & 0x7F for s in (21, 14, 7, 0))


def to_media(payload: bytes) -> bytes:
    """A Layer III stream that carries ``payload`` whole."""
    whole, rest = divmod(len(payload), ROOM)
    parts = []
    for i in range(0, whole * ROOM, ROOM):
        parts += (_FULL_LEAD, payload[i : i + ROOM])
    frames = whole
    if rest:
        size, lead = next(k for k in _KINDS if k[0] - LEAD >= rest)
        parts += (lead, payload[whole * ROOM :], bytes(size - LEAD - rest))
        frames += 1
    audio = b"".join(parts)
    fields = b"".join(b"TXXX" + _safe(len(v)) + b"\0\0" + v for v in (b"\3payload_bytes\0%d" % len(payload), b"\3payload_crc32\0%d" % zlib.crc32(payload)))
    tag = b"ID3\4\0\0" + _safe(len(fields)) + fields
    info_size, info_lead = next(k for k in _KINDS if k[0] >= LEAD + 116)
    total = info_size + len(audio)
    toc = bytes(min(255, 256 * (info_size + (frames * p // 100) * _FULL) // total) for p in range(100))
    info = info_lead + b"Xing" + (7).to_bytes(4, "big") + frames.to_bytes(4, "big") + total.to_bytes(4, "big") + toc
    return tag + info.ljust(info_size, b"\0") + audio


def header(word: int) -> tuple[int, int, int, int, bool] | None:
    """(frame bytes, samples, rate, side information bytes, has a checksum) of a 32-bit header, or None."""
    if word >> 16 & SYNC != SYNC:
        return None
    version, layer, bit, rate = word >> 19 & 3, 4 - (word >> 17 & 3), word >> 12 & 15, word >> 10 & 3
    if version == 1 or layer == 4 or bit in (0, 15) or rate == 3:
        return None
    one = version == 3
    kbps, hz, pad = BITRATES[one, layer][bit - 1], RATES[version][rate], word >> 9 & 1
    samples = 384 if layer == 1 else 1152 if layer == 2 or one else 576
    size = (12 * kbps * 1000 // hz + pad) * 4 if layer == 1 else samples // 8 * kbps * 1000 // hz + pad
    mono = word >> 6 & 3 == 3
    side = 0 if layer != 3 else (17 if mono else 32) if one else (9 if mono else 17)
    return size, samples, hz, side, not word >> 16 & 1


_seen_headers: dict = {}
_seen_checks: dict = {}


def _known(word: int):
    if word not in _seen_headers:
        if len(_seen_headers) > 50_000:
            _seen_headers.clear()
        _seen_headers[word] = header(word)
    return _seen_headers[word]


def crc16_bits(data: bytes, bits: int, start: bytes) -> int:
    """The same checksum over ``start`` and then the first ``bits`` bits of ``data``."""
    c = crc16(start + data[: bits // 8])
    for i in range(bits // 8 * 8, bits):
        top = c >> 15 ^ data[i // 8] >> 7 - i % 8 & 1
        c = (c << 1 & 0xFFFF) ^ (0x8005 if top else 0)
    return c


def protected_bits(word: int, body: bytes) -> int:
    """How many bits of ``body`` (what follows the checksum) the checksum of a Layer I or II frame covers."""
    one, layer, mode = word >> 19 & 3 == 3, 4 - (word >> 17 & 3), word >> 6 & 3
    channels = 1 if mode == 3 else 2
    joint = 4 * (word >> 4 & 3) + 4 if mode == 1 else 32  # subbands from here on share one allocation
    if layer == 1:
        return 4 * (32 if channels == 1 else 32 + joint)
    if not one:
        table = "low"
    else:
        kbps, hz = BITRATES[True, 2][(word >> 12 & 15) - 1] // channels, RATES[3][word >> 10 & 3]
        table = ("d" if hz == 32000 else "c") if kbps <= 48 else "a" if kbps <= 80 or hz == 48000 else "b"
    widths = [w for w, n in zip((4, 3, 2), ALLOCATIONS[table]) for _ in range(n)]
    bits = int.from_bytes(body[:48], "big")
    total, at, used = 8 * len(body[:48]), 0, 0
    for band, width in enumerate(widths):
        shared = channels == 2 and band >= joint
        for _ in range(1 if shared else channels):
            if at + width > total:
                return at
            used += (2 if shared else 1) * (bits >> total - at - width & (1 << width) - 1 > 0)
            at += width
    return at + 2 * used  # with two bits of scale factor selection for each allocated subband


def _checks(data: bytes, at: int, side: int) -> bool:
    word = int.from_bytes(data[at : at + 4], "big")
    if word >> 17 & 3 != 1:  # Layers I and II
        tail = data[at + 6 : at + 6 + 256]
        bits = protected_bits(word, tail)
        return bits <= 8 * len(tail) and crc16_bits(tail, bits, data[at + 2 : at + 4]) == int.from_bytes(data[at + 4 : at + 6], "big")
    body = data[at + 2 : at + 6 + side]
    good = _seen_checks.get(body)
    if good is None:
        if len(_seen_checks) > 50_000:
            _seen_checks.clear()
        good = _seen_checks[body] = crc16(body[:2] + body[4:]) == int.from_bytes(body[2:4], "big")
    return good


def _tags(data: bytes) -> tuple[dict[str, str], int, int]:
    """Tags of a stream and where its audio begins and ends."""
    tags, begin, end = {}, 0, len(data)
    while data[begin : begin + 3] == b"ID3" and len(data) - begin >= 10:
        major, flags = data[begin + 3], data[begin + 5]
        size = 0
        for b in data[begin + 6 : begin + 10]:
            size = size << 7 | b & 0x7F
        held = data[begin + 10 : begin + 10 + size]
        if flags & 0x80:  # unsynchronised: a zero byte was put behind each 255
            held = held.replace(b"\xff\0", b"\xff")
        at, stop = 0, len(held)
        if flags & 0x40 and stop >= 4:  # an extended header
            ext = int.from_bytes(held[:4], "big") if major == 3 else sum((b & 0x7F) << s for b, s in zip(held[:4], (21, 14, 7, 0)))
            at += ext + (4 if major == 3 else 0)
        while at + 10 <= stop and held[at : at + 4].strip(b"\0"):
            name = held[at : at + 4].decode("latin-1")
            raw = held[at + 4 : at + 8]
            n = int.from_bytes(raw, "big") if major == 3 else sum((b & 0x7F) << s for b, s in zip(raw, (21, 14, 7, 0)))
            body = held[at + 10 : min(at + 10 + n, stop)]
            if name[:1] == "T" and body:
                value = body[1:].decode({0: "latin-1", 1: "utf-16", 2: "utf-16-be"}.get(body[0], "utf-8"), "replace")
                key, _, value = value.partition("\0") if name == "TXXX" else (name, "", value)
                tags[key] = value.rstrip("\0")
            at += 10 + n
        begin += 10 + size + (10 if flags & 0x10 else 0)
    if end - begin >= 128 and data[end - 128 : end - 125] == b"TAG":
        last = data[end - 128 :]
        for name, a, b in (("title", 3, 33), ("artist", 33, 63), ("album", 63, 93), ("year", 93, 97)):
            if value := last[a:b].split(b"\0")[0].decode("latin-1").strip():
                tags.setdefault(name, value)
        end -= 128
    return tags, min(begin, end), end


def parse(data: bytes | None) -> dict:
    """What a stream holds; offsets are from its first byte, seconds are exact fractions."""
    data = data or b""
    tags, at, end = _tags(data)
    offsets, pieces, table = [], [], None
    samples = rate = good = bad = skipped = 0
    duration = Fraction(0)
    locked = True
    while at + 4 <= end:
        known = _known(int.from_bytes(data[at : at + 4], "big"))
        if known is None or at + known[0] > end or not (locked or _agrees(data, at + known[0], end)):
            locked = False  # damage: look for the next header that another one follows
            nxt = data.find(b"\xff", at + 1, end)
            skipped += (nxt if nxt >= 0 else end) - at
            at = nxt if nxt >= 0 else end
            continue
        locked = True
        size, n, hz, side, checked = known
        if checked:
            if _checks(data, at, side):
                good += 1
            else:
                bad += 1
        body = at + 4 + 2 * checked + side
        if table is None and not offsets and data[body : body + 4] in (b"Xing", b"Info"):
            table = _table(data, body, at)
        elif table is None and not offsets and data[at + 36 : at + 40] == b"VBRI":
            table = _vbri(data, at + 36, at)
        else:
            offsets.append(at)
            pieces.append(data[body : at + size])
            if rate and hz != rate:
                duration += Fraction(samples, rate)
                samples = 0
            rate = hz
            samples += n
        at += size
    skipped += max(0, end - at) if at < end else 0
    if rate:
        duration += Fraction(samples, rate)
    carried = b"".join(pieces)
    if tags.get("payload_bytes", "").isdigit():
        carried = carried[: int(tags["payload_bytes"])]
    whole = "payload_crc32" not in tags or tags["payload_crc32"] == str(zlib.crc32(carried))
    return {"tags": tags, "table": table, "offsets": offsets, "rate": rate, "samples": samples, "duration": duration, "checks_good": good, "checks_bad": bad, "skipped": skipped, "payload": carried, "payload_whole": whole}


def _agrees(data: bytes, at: int, end: int) -> bool:
    return at == end or at + 4 <= end and _known(int.from_bytes(data[at : at + 4], "big")) is not None


def _table(data: bytes, at: int, origin: int) -> dict:
    flags = int.from_bytes(data[at + 4 : at + 8], "big")
    out: dict = {"origin": origin}
    at += 8
    for bit, name in ((1, "frames"), (2, "bytes")):
        if flags & bit:
            out[name] = int.from_bytes(data[at : at + 4], "big")
            at += 4
    if flags & 4:
        out["toc"] = list(data[at : at + 100])
    return out


def _vbri(data: bytes, at: int, origin: int) -> dict:
    """The other kind of table: a count of bytes and frames and the bytes of each run of frames."""
    number = lambda i, n: int.from_bytes(data[at + i : at + i + n], "big")
    entries, scale, width = number(18, 2), number(20, 2), number(22, 2)
    runs = [scale * number(26 + i * width, width) for i in range(entries)]
    return {"origin": origin, "bytes": number(10, 4), "frames": number(14, 4), "frames_per_entry": number(24, 2), "runs": runs}


def seek(found: dict, seconds: Fraction) -> int | None:
    """Offset of the frame that plays at ``seconds``, exact for streams of one frame length."""
    if not found["offsets"]:
        return None
    per = Fraction(found["duration"], len(found["offsets"]))
    return found["offsets"][min(len(found["offsets"]) - 1, int(seconds / per))]


def _encode(batches):
    for batch in batches:
        for part in K.slices(batch, "text"):
            raw, bounds = K.buffers(part.column(1))
            raw, bounds = raw.tobytes(), bounds.tolist()
            sizes, media = [], []
            for a, b in zip(bounds, bounds[1:]):
                n = b - a
                media.append(to_media(raw[a:b] + bytes(max(64, -(-n // 64) * 64) - n)))
                sizes.append(n)
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], ["doc_id", "n_bytes", "media"])


def encode_media(docs: DataFrame) -> DataFrame:
    """``docs(doc_id, text)`` → doc_id, n_bytes, media (binary)."""
    ship(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(_encode, f"doc_id {kind}, n_bytes long, media binary")


_FIELDS = [("payload_bytes", "long"), ("payload_sha256", "string"), ("tail_crc32", "long"), ("media_bytes", "long"), ("media_sha256", "string"), ("feature", "string"), ("duration_num", "long"), ("duration_den", "long"), ("frames", "int"), ("table_frames", "int"), ("checks_bad", "int"), ("skipped_bytes", "long"), ("payload_whole", "boolean"), ("seek_offsets", "array<long>")]


def _measure(batches):
    import numpy as np

    for batch in batches:
        at = batch.schema.get_field_index("media")
        for part in K.slices(batch, "media"):
            rows = []
            for v in part.column(at):
                data = v.as_py() or b""
                f = parse(data)
                p, d = f["payload"], f["duration"]
                seeks = hashlib.sha256(np.array(f["offsets"], "<i8").tobytes()).hexdigest()[:16]
                feature = f"rate={f['rate']};frames={len(f['offsets'])};samples={f['samples']};seconds={d.numerator}/{d.denominator};checks={f['checks_good']}+{f['checks_bad']};seek={seeks}"
                rows.append((len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]), len(data), hashlib.sha256(data).hexdigest(), feature, d.numerator, d.denominator, len(f["offsets"]), (f["table"] or {}).get("frames"), f["checks_bad"], f["skipped"], f["payload_whole"], f["offsets"]))
            kinds = {"long": pa.int64(), "int": pa.int32(), "string": pa.string(), "boolean": pa.bool_(), "array<long>": pa.list_(pa.int64())}
            cols = [part.column(i) for i in range(at)] + [pa.array(c, kinds[k]) for c, (_, k) in zip(zip(*rows), _FIELDS)]
            yield pa.RecordBatch.from_arrays(cols, part.schema.names[:at] + [n for n, _ in _FIELDS])


def measure_media(media: DataFrame) -> DataFrame:
    """All columns before ``media`` plus payload digests, exact duration, checks and frame seek offsets."""
    ship(media.sparkSession)
    keep = media.select(*[c for c in media.columns if c != "media"], "media")
    schema = ", ".join([f"`{n}` {t}" for n, t in keep.dtypes[:-1]] + [f"{n} {t}" for n, t in _FIELDS])
    return keep.mapInArrow(_measure, schema)


def round_trip(docs: DataFrame) -> DataFrame:
    return measure_media(encode_media(docs))
