"""WARC archives of individually compressed records under a shared Zstandard dictionary.

A dictionary is built from records: parts from all over a record, header included, at most ``sample_bytes`` of each of
about ``samples`` pages, those with the least hashes of their ids. Both bounds are parameters and affect compression only.
Every archive begins with a skippable frame (magic 0x184D2A5D) that holds the dictionary, then a warcinfo record, and each
record is one Zstandard frame, so a reader needs nothing but the archive and can start at any record. Records with equal
payloads of ``least_revisit`` bytes or more are stored once: that with the smallest page id is the response, the others
are revisits that name it. ``date`` is the WARC-Date of all records, as pages carry none.

Only digests that repeat are joined back, from a stored table: as long as it can be broadcast pages are not shuffled,
beyond that a common digest's pages can be split between tasks.

Archives are rows (archive_id, content) of a table in the shared folder, each of about ``archive_bytes`` of payload: a
task that is run again writes the same rows. ``export`` writes them as .warc.zst files to any folder that the driver sees.

A null payload is an empty one; payloads shorter than the limit are all responses. Rows that repeat a page id and its
payload are of one kind. Ids may be whole numbers or strings and come back as they were; a null id is written without
one, null urls as empty. An empty table gives no archive. Columns other than those named are not read.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Iterator
from dataclasses import dataclass
from urllib.parse import quote, unquote

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import sliced, written

SKIPPABLE = 0x184D2A5D  # fixed value: the frame that holds a dictionary
VERSION = "WARC/1.1"


@dataclass(frozen=True)
class ArchiveRule:
    """Payload bytes an archive holds, dictionary size, pages it is built from and bytes of each, level, from where copies
    revisit, and the records' date."""

    archive_bytes: int = 8 << 20
    dictionary_bytes: int = 64 << 10
    samples: int = 1000
    sample_bytes: int = 16 << 10
    level: int = 3
    least_revisit: int = 100
    date: str = "1970-01-01T00:00:00Z"


def build_dictionary(payloads: list[bytes], size: int) -> bytes:
    """A trained dictionary, or the payloads' own last bytes where they are too few to train on."""
    try:
        return zstandard.train_dictionary(size, payloads).as_bytes()
    except zstandard.ZstdError:
        return b"".join(payloads)[-size:]


def _header(fields: list[tuple[str, object]]) -> bytes:
    return (VERSION + "\r\n" + "".join(f"{k}: {v}\r\n" for k, v in fields) + "\r\n").encode()


def _clean(url: str | None) -> str:
    return "".join(c for c in url or "" if c not in "\r\n")


def uri(page_id) -> str:
    """A record's id; percent signs keep any string within one header line."""
    return "<urn:page>" if page_id is None else f"<urn:page:{quote(str(page_id), safe='')}>"


def page_of(name: str | None) -> str | None:
    """The page id, as text, of a record's id."""
    return unquote(name[len("<urn:page:") : -1]) if name and name != "<urn:page>" else None


def record(page_id, url, payload: bytes, digest: str, refers_to, date: str = ArchiveRule.date) -> bytes:
    """A response or revisit record. A revisit has the payload's length and digest, but not the payload."""
    kind, body = ("response", payload) if refers_to is None else ("revisit", b"")
    fields = [("WARC-Type", kind), ("WARC-Record-ID", uri(page_id)), ("WARC-Date", date), ("WARC-Target-URI", _clean(url)), ("WARC-Payload-Digest", f"sha256:{digest}"), ("X-Payload-Length", len(payload))]
    if refers_to is not None:
        fields += [("WARC-Refers-To", uri(refers_to)), ("WARC-Profile", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")]
    return _header([*fields, ("Content-Type", "text/html; charset=utf-8"), ("Content-Length", len(body))]) + body + b"\r\n\r\n"


def info(date: str = ArchiveRule.date) -> bytes:
    """The record that an archive begins with."""
    body = b"format: WARC File Format 1.1\r\n"
    return _header([("WARC-Type", "warcinfo"), ("WARC-Record-ID", "<urn:info>"), ("WARC-Date", date), ("Content-Type", "application/warc-fields"), ("Content-Length", len(body))]) + body + b"\r\n\r\n"


def sample_of(whole: bytes, most: int) -> bytes:
    """``most`` bytes of a record: its start, and parts at even distances."""
    if len(whole) <= most:
        return whole
    part = most // 4
    step = (len(whole) - part) / 3
    return b"".join(whole[int(i * step) : int(i * step) + part] for i in range(4))


def write_archive(records: Iterator[bytes], dictionary: bytes, level: int = 3) -> bytes:
    """Dictionary frame, then one frame a record."""
    packer = zstandard.ZstdCompressor(level=level, dict_data=zstandard.ZstdCompressionDict(dictionary) if dictionary else None, write_content_size=True, write_checksum=True)
    return struct.pack("<II", SKIPPABLE, len(dictionary)) + dictionary + b"".join(packer.compress(r) for r in records)


def read_archive(content: bytes) -> Iterator[tuple[dict[str, str], bytes]]:
    """Headers and body of every record; raises where the archive is damaged."""
    magic, size = struct.unpack_from("<II", content)
    if magic != SKIPPABLE:
        raise ValueError("no dictionary frame")
    reader = zstandard.ZstdDecompressor(dict_data=zstandard.ZstdCompressionDict(content[8 : 8 + size]) if size else None)
    rest = memoryview(content)[8 + size :]
    while len(rest):
        frame = reader.decompressobj()
        raw = frame.decompress(rest)
        rest = rest[len(rest) - len(frame.unused_data) :]
        head, _, body = raw.partition(b"\r\n\r\n")
        lines = head.decode().split("\r\n")
        fields = dict(x.split(": ", 1) for x in lines[1:])
        length = int(fields["Content-Length"])
        if lines[0] != VERSION or body[length:] != b"\r\n\r\n":
            raise ValueError("damaged record")
        yield fields, body[:length]


def with_first(pages: DataFrame, rule: ArchiveRule = ArchiveRule()) -> DataFrame:
    """(page_id, url, html, digest, refers_to): revisits name the least page id among equal payloads. Only digests are
    shuffled, summed in each task first; what comes back is a row for each payload that repeats."""
    rows = pages.select("page_id", "url", F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    digest = F.sha2(F.col("html").cast("binary"), 256)
    keys = rows.where(F.octet_length("html") >= rule.least_revisit).select("page_id", digest.alias("digest")).groupBy("digest")
    firsts = written(keys.agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"), "firsts")
    out = rows.withColumn("digest", digest).join(firsts, "digest", "left")
    again = F.col("first").isNotNull() & ((F.col("page_id") != F.col("first")) | F.col("page_id").isNull())
    return out.select("page_id", "url", "html", "digest", F.when(again, F.col("first")).alias("refers_to"))


def dictionary_of(pages: DataFrame, rule: ArchiveRule = ArchiveRule()) -> bytes:
    """A dictionary out of the records of some ``samples`` pages, chosen by a limit on the ids' hashes."""
    share = min(1.0, rule.samples / max(1, pages.count()))
    some = pages.where("html IS NOT NULL").where(F.pmod(F.xxhash64("page_id"), F.lit(1 << 20)) < share * (1 << 20))
    some = some.select("page_id", "url", F.col("html").cast("string").alias("html"))

    def run(batches):
        for batch in batches:
            for part in sliced(batch, "html"):
                out = []
                for p, u, h in zip(*(part[c].to_pylist() for c in ("page_id", "url", "html")), strict=True):
                    payload = h.encode()
                    out.append(sample_of(record(p, u, payload, hashlib.sha256(payload).hexdigest(), None, rule.date), rule.sample_bytes))
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.binary())], ["part"])

    parts = [bytes(r["part"]) for r in some.mapInArrow(run, "part binary").collect()]  # some samples * sample_bytes
    return build_dictionary(sorted(parts), rule.dictionary_bytes)


def archives(pages: DataFrame, rule: ArchiveRule = ArchiveRule()) -> DataFrame:
    """(archive_id, content), stored in the shared folder."""
    rows = with_first(pages, rule)
    dictionary = dictionary_of(pages, rule)

    def run(batches):
        held, size, made = [], 0, 0

        def archive():
            nonlocal held, size, made
            content = write_archive(iter([info(rule.date), *held]), dictionary, rule.level)
            name = hashlib.sha256(content).hexdigest()[:32]
            held, size, made = [], 0, made + 1
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([content], pa.binary())], ["archive_id", "content"])

        for batch in batches:
            for part in sliced(batch, "html"):
                for p, u, h, d, r in zip(*(part[c].to_pylist() for c in ("page_id", "url", "html", "digest", "refers_to")), strict=True):
                    payload = h.encode()
                    held.append(record(p, u, payload, d, r, rule.date))
                    size += len(payload)
                    if size >= rule.archive_bytes:
                        yield archive()
        if held:
            yield archive()

    return written(rows.mapInArrow(run, "archive_id string, content binary"), "archives")


def records(table: DataFrame, id_type: str = "bigint") -> DataFrame:
    """What the archives hold: page_id, url, record_type, payload_digest, payload_bytes, refers_to, body. The body of a
    response is checked against its digest and length."""

    fields = [("page_id", pa.string()), ("url", pa.string()), ("record_type", pa.string()), ("payload_digest", pa.string()), ("payload_bytes", pa.int64()), ("refers_to", pa.string()), ("body", pa.binary())]

    def run(batches):
        schema = pa.schema(fields)
        made = lambda rows: pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema=schema)
        for batch in batches:
            for content in batch["content"]:
                rows, size = [], 0
                for f, body in read_archive(content.as_py()):
                    if f["WARC-Type"] == "warcinfo":
                        continue
                    digest, length = f["WARC-Payload-Digest"].removeprefix("sha256:"), int(f["X-Payload-Length"])
                    if f["WARC-Type"] == "response" and (len(body) != length or hashlib.sha256(body).hexdigest() != digest):
                        raise ValueError("payload differs from its digest")
                    rows.append((page_of(f["WARC-Record-ID"]), f["WARC-Target-URI"], f["WARC-Type"], digest, length, page_of(f.get("WARC-Refers-To")), body))
                    size += len(body)
                    if size > 4 << 20:
                        yield made(rows)
                        rows, size = [], 0
                if rows:
                    yield made(rows)

    out = table.mapInArrow(run, "page_id string, url string, record_type string, payload_digest string, payload_bytes bigint, refers_to string, body binary")
    return out.withColumns({c: F.col(c).cast(id_type) for c in ("page_id", "refers_to")}) if id_type != "string" else out


def export(table: DataFrame, folder: str) -> list[str]:
    """The archives as files, one at a time through the driver."""
    import os

    os.makedirs(folder, exist_ok=True)
    out = []
    for r in table.toLocalIterator():
        out.append(f"{folder}/{r.archive_id}.warc.zst")
        with open(out[-1], "wb") as f:
            f.write(r.content)
    return out


def digest(pages: DataFrame, rule: ArchiveRule = ArchiveRule()) -> DataFrame:
    """Writes the archives, reads them back, and returns the contract's columns as they are in the records."""
    kind = dict(pages.dtypes)["page_id"]
    return records(archives(pages, rule), kind).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


# The same rows in SQL.
SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
     d AS (SELECT page_id, strlen(html) AS payload_bytes, sha256(html) AS payload_digest FROM p),
     f AS (SELECT payload_digest, min(page_id) AS first_id FROM d WHERE payload_bytes >= 100 GROUP BY payload_digest)
SELECT d.page_id, CAST(d.payload_bytes AS BIGINT) AS payload_bytes, d.payload_digest,
       CASE WHEN f.first_id IS NOT NULL AND f.first_id <> d.page_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN f.first_id IS NOT NULL AND f.first_id <> d.page_id THEN f.first_id END AS refers_to
FROM d LEFT JOIN f ON f.payload_digest = d.payload_digest
"""
