"""Ogg media columns: pages with checksums, packets from lacing values, several logical streams, timestamps.

``write_ogg`` stores 8-bit samples losslessly, woven over two logical streams like channels;
``read_ogg`` verifies every page, reassembles and demultiplexes the packets and derives their
times from the granule positions.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpus_audit.llm.common import whole_text

#: Six lacing values a packet and fifty a page: every ninth packet goes on over a page's end.
RATE, PACKET, STREAMS, PAGE_SEGMENTS = 8000, 1500, 2, 50
CONTINUED, FIRST, LAST = 1, 2, 4
_HEADER = struct.Struct("<4sBBqIIIB")
_MAGIC = b"RAW8\x00"
_REVERSED = bytes(int(f"{b:08b}"[::-1], 2) for b in range(256))


def page_checksum(page: bytes) -> int:
    """The format's CRC (polynomial 0x04c11db7, most significant bit first, start 0), via the reflected one."""
    low_first = zlib.crc32(page.translate(_REVERSED), 0xFFFFFFFF) ^ 0xFFFFFFFF
    return int.from_bytes(low_first.to_bytes(4, "little").translate(_REVERSED), "big")


def _page(flags: int, granule: int, serial: int, number: int, lacing: bytes, body: bytes) -> bytes:
    head = _HEADER.pack(b"OggS", 0, flags, granule, serial, number, 0, len(lacing))
    raw = head + lacing + body
    return raw[:22] + page_checksum(raw).to_bytes(4, "little") + raw[26:]


def stream_pages(packets: list[tuple[bytes, int]], serial: int) -> list[tuple[int, bytes]]:
    """(granule, page) of one logical stream; the first packet stands alone on its page."""
    pages, number = [], 0
    lacing, body, granule, continued = bytearray(), bytearray(), -1, False

    def flush(last: bool) -> None:
        nonlocal lacing, body, granule, continued, number
        flags = CONTINUED * continued | FIRST * (number == 0) | LAST * last
        pages.append((granule, _page(flags, granule, serial, number, bytes(lacing), bytes(body))))
        continued = bool(lacing) and lacing[-1] == 255
        lacing, body, granule, number = bytearray(), bytearray(), -1, number + 1

    for i, (packet, end) in enumerate(packets):
        values = [255] * (len(packet) // 255) + [len(packet) % 255]
        at = 0
        for value in values:
            if len(lacing) == PAGE_SEGMENTS:
                flush(False)
            lacing.append(value)
            body += packet[at : at + value]
            at += value
        granule = end
        if i == 0 and len(packets) > 1:
            flush(False)
    flush(True)
    return pages


def write_ogg(samples: bytes, serial: int) -> bytes:
    """8-bit samples as an Ogg file: sample i belongs to logical stream i mod ``STREAMS``, like a channel.

    Granule positions count a stream's own samples. Equal samples give equal files.
    """
    paged = []
    for k in range(STREAMS):
        own = samples[k::STREAMS]
        cuts = [(own[i : i + PACKET], min(i + PACKET, len(own))) for i in range(0, len(own), PACKET)]
        paged.append(stream_pages([(_MAGIC + struct.pack("<IBB", RATE, k, STREAMS), 0), *cuts], serial + k))
    # First pages come first; then pages follow in the order of their end positions.
    rest = []
    for k, pages in enumerate(paged):
        at = 0
        for j, (granule, page) in enumerate(pages[1:]):
            at = granule if granule >= 0 else at
            rest.append((at, k, j, page))
    return b"".join(pages[0][1] for pages in paged) + b"".join(x[3] for x in sorted(rest, key=lambda x: x[:3]))


@dataclass
class LogicalStream:
    serial: int
    packets: list[tuple[int, bytes]] = field(default_factory=list)  # (end granule, data), without the header
    header: bytes | None = None
    pages: int = 0
    partial: bytearray | None = None
    ended: bool = False


@dataclass
class OggFile:
    streams: dict[int, LogicalStream]
    pages: int
    bad_pages: int

    def timeline(self) -> list[tuple[float, float, int, bytes]]:
        """(start second, end second, serial, data) of all data packets in time order."""
        timed = [((end - len(data)) / RATE, end / RATE, s.serial, data) for s in self.streams.values() for end, data in s.packets]
        return sorted(timed, key=lambda x: x[:3])

    def samples(self) -> bytes:
        """The channels, taken from the streams' header packets, woven together again."""
        channels = {s.header[len(_MAGIC) + 4]: b"".join(data for _, data in s.packets) for s in self.streams.values() if s.header}
        out = bytearray(sum(map(len, channels.values())))
        for k, own in channels.items():
            out[k::STREAMS] = own
        return bytes(out)


def read_ogg(raw: bytes) -> OggFile:
    """Parse a file; pages with a wrong checksum or version are counted and skipped, gaps in the page numbers are counted.

    A packet of which a part is on a lost page is dropped whole: what was held of it, and what a continued page
    begins with.
    """
    found = OggFile({}, 0, 0)
    at = 0
    while (at := raw.find(b"OggS", at)) >= 0 and at + _HEADER.size <= len(raw):
        _, version, flags, granule, serial, number, crc, segments = _HEADER.unpack_from(raw, at)
        lacing = raw[at + 27 : at + 27 + segments]
        end = at + 27 + segments + sum(lacing)
        page = raw[at:end]
        if version or end > len(raw) or page_checksum(page[:22] + bytes(4) + page[26:]) != crc:
            found.bad_pages, at = found.bad_pages + 1, at + 4
            continue
        stream = found.streams.setdefault(serial, LogicalStream(serial))
        if number != stream.pages or bool(flags & CONTINUED) != (stream.partial is not None):
            found.bad_pages += 1
            stream.partial = None
        stream.pages, found.pages = number + 1, found.pages + 1
        body, done = 27 + segments, []
        torn = bool(flags & CONTINUED) and stream.partial is None
        whole = stream.partial if stream.partial is not None else bytearray()
        open_ = False
        for value in lacing:
            whole += page[body : body + value]
            body += value
            open_ = value == 255
            if not open_:
                if not torn:
                    done.append(bytes(whole))
                torn, whole = False, bytearray()
        stream.partial = whole if open_ and not torn else None
        if flags & FIRST and done and done[0].startswith(_MAGIC):
            stream.header = done.pop(0)
        # The granule is the end of the last packet that ends here; each earlier one ends where the next begins.
        ends = granule
        for k in range(len(done) - 1, -1, -1):
            done[k], ends = (ends, done[k]), ends - len(done[k])
        stream.packets += done
        stream.ended |= bool(flags & LAST)
        at = end
    return found


def digest_row(text: bytes) -> tuple:
    """The stored form of one text and what is read back from it."""
    payload = text + bytes(-len(text) % 64 or (0 if text else 64))
    media = write_ogg(payload, zlib.crc32(payload) & 0x7FFFFFFE)
    file = read_ogg(media)
    timed = file.timeline()
    back = file.samples()
    feature = f"streams={len(file.streams)};pages={file.pages};bad={file.bad_pages};packets={len(timed)};seconds={max((x[1] for x in timed), default=0.0):.3f};mean={sum(back) / len(back):.3f}"
    return (len(text), len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-64:]), len(media), hashlib.sha256(media).hexdigest(), feature, len(file.streams), file.pages, len(timed), file.bad_pages == 0 and back == payload)


_DIGEST = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, n_streams int, n_pages int, n_packets int, verified boolean"


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int32(), pa.int32(), pa.int32(), pa.bool_()]
    names = [x.split()[0] for x in _DIGEST.split(", ")]
    for batch in batches:
        rows = [digest_row(x.as_py().encode()) for x in batch.column("text")]
        columns = list(zip(*rows, strict=True)) if rows else [()] * len(kinds)
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, type=k) for c, k in zip(columns, kinds, strict=True))], names=names)


def mux(docs: DataFrame) -> DataFrame:
    """``doc_id, media``: each text as an Ogg file in a binary column (null text: empty)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            payloads = [(t := x.as_py().encode()) + bytes(-len(t) % 64 or (0 if t else 64)) for x in batch.column("text")]
            media = [write_ogg(p, zlib.crc32(p) & 0x7FFFFFFE) for p in payloads]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(media, type=pa.binary())], names=["doc_id", "media"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(run, "doc_id long, media binary")


def demux(files: DataFrame, key: str = "doc_id", media: str = "media") -> DataFrame:
    """One row per packet of each file: key, serial, packet number, start and end second, data. Null media has none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k, raw in zip(batch.column("key"), batch.column("media"), strict=True):
                rows = [(k.as_py(), s, i, a, b, d) for i, (a, b, s, d) in enumerate(read_ogg(raw.as_py()).timeline())]
                columns = list(zip(*rows, strict=True)) if rows else [()] * 6
                kinds = [pa.int64(), pa.int64(), pa.int32(), pa.float64(), pa.float64(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array(c, type=t) for c, t in zip(columns, kinds, strict=True)], names=["key", "serial", "packet", "start_s", "end_s", "data"])

    return files.filter(F.col(media).isNotNull()).select(F.col(key).cast("long").alias("key"), F.col(media).alias("media")).mapInArrow(run, "key long, serial long, packet int, start_s double, end_s double, data binary")


def op3_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every text's stored form and read-back digests.

    Null and empty texts are 64 bytes of 0; texts of any length are stored whole; repeated rows repeat; a null doc_id stays
    null; an empty table gives an empty result; columns other than doc_id and text are not read.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(_digest, _DIGEST)
