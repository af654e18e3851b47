"""WARC archives: written natively, read back by boundary-chain verification.

Writing. A record's text form ends with two line breaks, so a text sink whose line separator is those breaks writes plain
WARC files, through any store and with Spark's commit protocol. Equal payloads of a given size are stored once: the row
with the smallest id is the response, later ones revisit it.

Reading. Every place where a record could begin is a candidate: the magic of a version line, a readable header, a length,
and the offset where a successor would begin. Payloads may hold such magic too. Candidates become rows (file, offset,
successor); pointer jumping from offset 0, doubling the step each round, keeps those on the chain of true records.
"""

from __future__ import annotations

import base64
import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privgrove.llm.textio import shared_dir, stored

MAGIC, BREAK = b"WARC/1.", "\r\n"
END = BREAK + BREAK
#: Payload bytes that one archive file holds, about.
FILE_BYTES = 24 << 20
DATE = "2024-01-01T00:00:00Z"


def base32_sha1(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def digest_column(payload: Column) -> Column:
    """Upper-case base32 SHA-1 of binary payload, from its hex form: five hex digits are four base32 digits."""
    hexed = F.sha1(payload)
    groups = [F.lpad(F.conv(F.substring(hexed, k, 5), 16, 32), 4, "0") for k in range(1, 41, 5)]
    digits = "0123456789ABCDEFGHIJKLMNOPQRSTUV"
    return F.translate(F.concat(*groups), digits, "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def with_revisits(pages: DataFrame, least_bytes: int, id_col: str, html_col: str, url_col: str, at: str) -> DataFrame:
    """(page_id, url, html, digest, size, refers_to); refers_to only where the page revisits another.

    A row is decided by its own id and payload, so where an id repeats its other payloads are not touched. Only (id,
    digest) meets the rows again: rows of one payload, however many, are spread by their ids.
    """
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.coalesce(F.col(url_col).cast("string"), F.lit("")).alias("url"), F.coalesce(F.col(html_col).cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("digest", digest_column(F.encode("html", "UTF-8"))).withColumn("size", F.octet_length("html").cast("long"))
    keyed = rows.where(F.col("size") >= least_bytes).select("page_id", "digest")
    first = keyed.groupBy("digest").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("held")).where("held > 1")
    later = keyed.join(first, "digest").where("page_id > first").select("page_id", "digest", F.col("first").alias("refers_to")).distinct()
    return rows.join(stored(later, "revisits", at), ["page_id", "digest"], "left").select("page_id", "url", "html", "digest", "size", "refers_to")


def record_text(revisit: Column) -> Column:
    """A record without its final breaks: header lines, an empty line, and the payload unless it revisits."""
    lines = [
        F.lit("WARC/1.1"),
        F.concat(F.lit("WARC-Type: "), F.when(revisit, "revisit").otherwise("response")),
        F.concat(F.lit("WARC-Record-ID: <urn:page:"), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.lit(">")),
        F.lit(f"WARC-Date: {DATE}"),
        F.concat(F.lit("WARC-Target-URI: "), F.regexp_replace("url", "[\\r\\n]", "")),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest")),
        F.concat(F.lit("X-Payload-Length: "), F.col("size").cast("string")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: <urn:page:"), F.col("refers_to").cast("string"), F.lit(">"))),
        F.concat(F.lit("Content-Length: "), F.when(revisit, F.lit("0")).otherwise(F.col("size").cast("string"))),
    ]
    return F.concat(F.concat_ws(BREAK, *lines), F.lit(END), F.when(revisit, F.lit("")).otherwise(F.col("html")))


def write_archives(pages: DataFrame, path: str, least_bytes: int = 0, id_col: str = "page_id", html_col: str = "html", url_col: str = "url", file_bytes: int = FILE_BYTES) -> None:
    """Write one record per row. Null html is an empty payload; a null id is written empty and read as null."""
    rows = with_revisits(pages, least_bytes, id_col, html_col, url_col, f"{path}_work")
    size = rows.agg(F.avg(F.col("size") + F.octet_length("url"))).first()[0] or 0
    each = max(1, int(file_bytes / (size + 400)))
    rows.select(record_text(F.col("refers_to").isNotNull()).alias("value")).write.mode("overwrite").option("lineSep", END).option("maxRecordsPerFile", each).text(path)


CRLF, BLANK = b"\r\n", b"\r\n\r\n"


def candidates(raw: bytes) -> Iterator[tuple[int, int, dict[str, str], int]]:
    """(offset, successor, header fields, payload start) of every place where a record could begin.

    A candidate begins a line, has a version line and a header with a length that stays inside the file and is followed
    by the closing breaks. Others can't be records, whatever the chain. A header has any length and ends at the first
    blank line; no line of it is another version line, so of several before one blank line only the last is a candidate
    and every byte is searched once.
    """
    at = raw.find(MAGIC)
    while at >= 0:
        if at == 0 or raw[at - 2 : at] == CRLF:
            end = raw.find(BLANK, at)
            if end < 0:
                return
            last = raw.rfind(CRLF + MAGIC, at, end)
            at = at if last < 0 else last + len(CRLF)
            lines = raw[at:end].decode("utf-8", "replace").split("\r\n")
            fields = {k.strip().lower(): v.strip() for k, sep, v in (line.partition(":") for line in lines[1:]) if sep}
            length = fields.get("content-length", "")
            if length.isascii() and length.isdigit():
                start = end + len(BLANK)
                stop = start + int(length)
                if raw[stop : stop + 4] == BLANK:
                    yield at, stop + 4, fields, start
        at = raw.find(MAGIC, at + 1)


def candidate_rows(archives: DataFrame) -> DataFrame:
    """One row per candidate of the archive files (path, content), and one without a type for each file's end."""

    def scan(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, content in zip(batch.column("path"), batch.column("content")):
                raw, rows = content.as_py(), []
                for at, successor, fields, start in candidates(raw):
                    kind, payload = fields.get("warc-type", ""), raw[start : successor - 4]
                    full = kind != "revisit"
                    stated = fields.get("x-payload-length", "")
                    rows.append(
                        (
                            at,
                            successor,
                            number(fields.get("warc-record-id")),
                            len(payload) if full else int(stated) if stated.isdigit() else None,
                            base32_sha1(payload) if full else fields.get("warc-payload-digest", "").removeprefix("sha1:"),
                            kind,
                            number(fields.get("warc-refers-to")),
                        )
                    )
                rows.append((len(raw), len(raw), None, None, None, None, None))
                columns = [pa.array([path.as_py()] * len(rows), pa.string()), *(pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64())))]
                yield pa.RecordBatch.from_arrays(columns, names=["file", "at", "successor", "page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"])

    return archives.select("path", "content").mapInArrow(scan, "file string, at long, successor long, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long")


def number(name: str | None) -> int | None:
    found = re.fullmatch(r"<urn:page:(-?\d+)>", name or "")
    return int(found[1]) if found else None


def reachable(found: DataFrame) -> DataFrame:
    """The candidates on the chain from offset 0 of their file, by pointer jumping within each file.

    Marks start at offset 0. Each round marks the targets of marked pointers and replaces every pointer by its pointer's
    pointer, so a chain of n records takes log2(n) rounds. A file's rows are its offsets only, about one per record. A
    chain that does not reach the file's end is an error: what lies behind the break would be lost.
    """

    def jump(table: pa.Table) -> pa.Table:
        at, goes = table["at"].to_numpy(), table["successor"].to_numpy()
        order = np.argsort(at, kind="stable")
        places, none = at[order], len(at)
        target = np.searchsorted(places, goes[order])
        real = places[np.minimum(target, none - 1)] == goes[order]
        pointer = np.append(np.where(real, target, none), none)
        marked = np.zeros(none + 1, bool)
        marked[0] = places[0] == 0
        before = -1
        while marked.sum() != before:
            before = marked.sum()
            marked[pointer[marked]] = True
            marked[none] = False
            pointer = pointer[pointer]
        if not marked[none - 1]:
            raise ValueError(f"{table['file'][0]}: the chain of records breaks off at byte {places[marked[:none]].max(initial=0)}")
        return table.take(pa.array(order[marked[:none]])).select(["file", "at"])

    chain = found.select("file", "at", "successor").groupBy("file").applyInArrow(jump, "file string, at long")
    return found.join(chain, ["file", "at"], "left_semi")


def read_archives(spark, path: str, at: str) -> DataFrame:
    """The true records of the archives below path: page_id, payload_bytes, payload_digest, record_type, refers_to."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path)
    found = stored(candidate_rows(files), "candidates", at)
    return reachable(found).where("record_type IS NOT NULL").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def archived(pages: DataFrame, least_bytes: int = 0, path: str | None = None, **columns) -> DataFrame:
    """Write archives of all pages, read them back and give one row per page.

    Of pages with equal payloads of at least least_bytes, the one with the smallest id is the response. Null payloads are
    empty ones. Each row is decided by its own id and payload: an id that repeats can be a response with one payload and a
    revisit with another, and rows that repeat the smallest id of a payload are responses each. Null ids never revisit.
    Extra columns are ignored, whatever their names; an empty table gives no rows.
    """
    path = path or f"{shared_dir(pages.sparkSession)}/warc"
    write_archives(pages, path, least_bytes, **columns)
    return read_archives(pages.sparkSession, path, f"{path}_work")
