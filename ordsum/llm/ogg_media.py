"""Media columns in Ogg: pages with checksums, lacing, logical streams, granule times.

The container is built and read as its public specification (RFC 3533) lays down:
27 header bytes, a segment table of lacing values, page checksums with the
polynomial 0x04c11db7, packets that may run over several pages, any number of
logical streams told apart by serial number, and a granule position per page.

Cases: null bytes are an empty payload; a damaged page is counted, not used, and
never raises; a packet whose continuation is lost is dropped and counted; bytes
between pages are skipped. Rows are independent, so ties, repeats, empty tables and
further columns change nothing.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RATE = 8000
FRAME = 4080  # samples in a packet: 16 full lacing values and a final zero
NO_GRANULE = 0xFFFFFFFFFFFFFFFF
CONTINUED, FIRST, LAST = 1, 2, 4
HEADER = struct.Struct("<4sBBQIIIB")
START = struct.Struct("<8sIHHQ")  # name, rate, streams, this stream, samples of all
NAME = b"PCM8MUX\0"

_MIRROR = bytes(int(f"{i:08b}"[::-1], 2) for i in range(256))


def page_checksum(page: bytes) -> int:
    """Unreflected CRC-32 from zero, by way of zlib's reflected one on mirrored bytes."""
    raw = zlib.crc32(page.translate(_MIRROR), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(raw.to_bytes(4, "little").translate(_MIRROR), "big")


def _page(flags: int, granule: int, serial: int, seq: int, lacing: bytes, body: bytes) -> bytes:
    head = HEADER.pack(b"OggS", 0, flags, granule, serial, seq, 0, len(lacing)) + lacing
    whole = head + body
    return whole[:22] + page_checksum(whole).to_bytes(4, "little") + whole[26:]


def paginate(serial: int, packets: list[tuple[bytes, int]]) -> list[bytes]:
    """One logical stream as pages. packets: bytes and the granule position at their end.

    The first packet, the stream's header, has a page of its own."""
    pages: list[bytes] = []
    lacing, parts, granule, resumed = bytearray(), [], NO_GRANULE, False

    def flush(last: bool) -> None:
        nonlocal granule
        flags = CONTINUED * resumed | FIRST * (not pages) | LAST * last
        pages.append(_page(flags, granule, serial, len(pages), bytes(lacing), b"".join(parts)))
        lacing.clear()
        parts.clear()
        granule = NO_GRANULE

    for i, (packet, end) in enumerate(packets):
        values = b"\xff" * (len(packet) // 255) + bytes([len(packet) % 255])
        at = 0
        while values:
            room = 255 - len(lacing)
            take, values = values[:room], values[room:]
            lacing += take
            size = sum(take)
            parts.append(packet[at : at + size])
            at += size
            if not values:
                granule = end
            if len(lacing) == 255 and (values or i + 1 < len(packets)):
                flush(False)
                resumed = bool(values)
        if i == 0 and len(packets) > 1 and lacing:
            flush(False)
            resumed = False
    flush(True)
    return pages


def store(payload: bytes, streams: int = 2, serial: int = 1) -> bytes:
    """Payload as 8-bit samples, dealt frame by frame to logical streams whose pages alternate."""
    frames = [payload[i : i + FRAME] for i in range(0, len(payload), FRAME)]
    lanes = []
    for k in range(min(streams, max(1, len(frames)))):
        own, done, packets = frames[k::streams], 0, [(START.pack(NAME, RATE, streams, k, len(payload)), 0)]
        for x in own:
            done += len(x)
            packets.append((x, done))
        lanes.append(paginate(serial + k, packets))
    # all first pages come before any other page
    out = [lane[0] for lane in lanes]
    for i in range(1, max(map(len, lanes))):
        out += [lane[i] for lane in lanes if i < len(lane)]
    return b"".join(out)


def read_pages(data: bytes) -> Iterator[tuple[int, int, int, int, bytes, bytes, bool]]:
    """(flags, granule, serial, sequence, lacing, body, sound) of each page found."""
    at = 0
    while (at := data.find(b"OggS", at)) >= 0:
        if at + 27 > len(data):
            return
        _, version, flags, granule, serial, seq, crc, n = HEADER.unpack_from(data, at)
        lacing = data[at + 27 : at + 27 + n]
        end = at + 27 + n + sum(lacing)
        if version != 0 or len(lacing) < n or end > len(data):
            at += 4
            continue
        page = data[at:end]
        sound = page_checksum(page[:22] + b"\0\0\0\0" + page[26:]) == crc
        yield flags, granule, serial, seq, lacing, page[27 + n :], sound
        at = end if sound else at + 4


class Demuxed:
    """Packets of each logical stream, with end times in samples, and what went wrong."""

    def __init__(self) -> None:
        self.packets: dict[int, list[tuple[bytes, int | None]]] = {}
        self.pages = self.bad_pages = self.lost_packets = self.gaps = 0


def demultiplex(data: bytes) -> Demuxed:
    out = Demuxed()
    tails: dict[int, bytes | None] = {}
    expected: dict[int, int] = {}
    for flags, granule, serial, seq, lacing, body, sound in read_pages(data):
        out.pages += 1
        if not sound:
            out.bad_pages += 1
            continue
        done = out.packets.setdefault(serial, [])
        tail = tails.get(serial)
        if expected.get(serial, seq) != seq:
            out.gaps += 1
            if tail is not None:
                out.lost_packets += 1
            tail = None
        orphan = bool(flags & CONTINUED) and tail is None
        if tail is not None and not flags & CONTINUED:
            out.lost_packets += 1
            tail = None
        first, at, size, held = len(done), 0, 0, tail or b""
        for v in lacing:
            size += v
            if v < 255:
                if orphan:
                    out.lost_packets += 1
                    orphan = False
                else:
                    done.append((held + body[at : at + size], None))
                held, at, size = b"", at + size, 0
        tails[serial] = held + body[at : at + size] if lacing and lacing[-1] == 255 and not orphan else None
        expected[serial] = seq + 1
        if granule != NO_GRANULE:  # the last packet that ends here ends at the page's granule position
            end = granule
            for i in range(len(done) - 1, first - 1, -1):
                done[i] = (done[i][0], end)
                end -= len(done[i][0])
    return out


def restore(data: bytes) -> tuple[bytes, Demuxed]:
    """The payload read back from the stored bytes."""
    got = demultiplex(data)
    lanes: dict[int, list[tuple[bytes, int | None]]] = {}
    streams = 1
    for packets in got.packets.values():
        if packets and packets[0][0].startswith(NAME):
            _, _, streams, lane, _ = START.unpack(packets[0][0])
            lanes[lane] = packets[1:]
    most = max(map(len, lanes.values()), default=0)
    return b"".join(lanes[k][i][0] for i in range(most) for k in range(streams) if k in lanes and i < len(lanes[k])), got


def features(payload: bytes, got: Demuxed) -> str:
    samples = np.frombuffer(payload, np.uint8)
    ends = [e for p in got.packets.values() for _, e in p if e is not None]
    return (
        f"pages={got.pages};bad={got.bad_pages};lost={got.lost_packets};streams={len(got.packets)}"
        f";packets={sum(map(len, got.packets.values()))};last_us={max(ends, default=0) * 1_000_000 // RATE}"
        f";peak={int(samples.max(initial=0))};sum={int(samples.sum(dtype=np.int64))}"
    )


def with_ogg(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", media_col: str = "media") -> DataFrame:
    """(id, n_bytes, media): the text of each row as UTF-8, zero-padded to a positive multiple of 64, in Ogg."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 512) for i in range(0, batch.num_rows, 512)):
                sizes, media = [], []
                for t in part.column(1).to_pylist():
                    raw = (t or "").encode("utf-8", "surrogatepass")
                    sizes.append(len(raw))
                    media.append(store(raw + bytes(-len(raw) % 64 or (0 if raw else 64))))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64()), pa.array(media, pa.binary())], names=["id", "n_bytes", "media"])

    src = df.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("t"))
    return src.mapInArrow(run, "id long, n_bytes long, media binary").toDF(id_col, "n_bytes", media_col)


def ogg_facts(df: DataFrame, id_col: str = "doc_id", media_col: str = "media") -> DataFrame:
    """Reads a column of Ogg files back: digests of payload and file, stream facts."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows: list[tuple] = []
            for data in batch.column(1).to_pylist():
                payload, got = restore(data or b"")
                rows.append((len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(data or b""), hashlib.sha256(data or b"").hexdigest(), features(payload, got), got.bad_pages))
            cols = list(zip(*rows)) or [()] * 7
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64()]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(cols, kinds))], names=["id", *"abcdefg"])

    got = df.select(F.col(id_col).alias("id"), media_col).mapInArrow(run, "id long, a long, b string, c long, d long, e string, f string, g long")
    return got.toDF(id_col, "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature", "bad_pages")


def op1_ogg(docs: DataFrame) -> DataFrame:
    """Digest columns of the round trip for every document."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
        for batch in batches:
            rows = []
            for i, n, media in zip(*(c.to_pylist() for c in batch.columns)):
                payload, got = restore(media)
                rows.append((i, n, len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(media), hashlib.sha256(media).hexdigest(), features(payload, got)))
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [()] * 8, kinds)], names=names)

    return with_ogg(docs).mapInArrow(run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")
