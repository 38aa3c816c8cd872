"""Web archives: records written as plain text files, and read back by verifying the chain of boundaries.

Writing goes through Spark's own text writer, the record terminator being the line separator, so files
are committed by Spark's protocol in any store and a lost executor leaves none half written. Every file
starts with a record, records lie end to end, and files hold a bounded number of records.

Reading takes every place where a record could begin, real or part of a payload, parses its header and
emits the offset of the place where its successor would begin. Pointer jumping from the start of each file,
doubling the reach each round, keeps the records on the chain; a record header inside a payload is on no
chain that starts there and goes.

Of records with equal payloads of at least ``least_bytes`` bytes the one with the smallest id is a response
and the others revisit it.

Edge cases: null pages have empty payloads; a null id is written as ``-`` and read as null; repeated
ids are told apart from their revisits by digest only, a row equal to the response in id and payload being a
response itself; an empty table writes no record; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import map_batches, small_enough, written

CRLF = "\r\n"
MAGIC = b"WARC/1.0\r\n"
END = b"\r\n\r\n"
RECORD = "key {}, url string, payload_bytes long, payload_digest string, record_type string, refers_to {}"


def mark_revisits(pages: DataFrame, id_col: str, url_col: str, html_col: str, least_bytes: int, broadcast_rows: int = 500_000) -> DataFrame:
    """Pages with payload, its size and digest, and the id of the response to which a revisit refers.

    Only (digest, id) pairs are shuffled for the smallest id of each digest. Digests of more than one page are sent to
    the pages when there are at most ``broadcast_rows`` of them (some 50 MB); beyond that pages meet them in a join that
    Spark may split where one digest is frequent.
    """
    html = F.coalesce(F.col(html_col), F.lit(""))
    rows = pages.select(F.col(id_col).alias("key"), F.col(url_col).alias("url"), html.alias("payload"), F.octet_length(html).cast("long").alias("size"), F.sha2(html.cast("binary"), 256).alias("digest"))
    large = F.col("size") >= least_bytes
    counted = rows.where(large).groupBy("digest").agg(F.min("key").alias("response"), F.count(F.lit(1)).alias("copies"))
    responses = written(counted.where("copies > 1").drop("copies"), "responses")
    responses = F.broadcast(responses) if small_enough(responses, broadcast_rows) else responses
    return rows.join(responses, (rows.digest == responses.digest) & large, "left").select(rows["*"], F.when(F.col("key") != F.col("response"), F.col("response")).alias("refers_to"))


def record_text(media_type: str = "text/html; charset=utf-8") -> Column:
    """A whole record but for its terminator."""
    is_revisit = F.col("refers_to").isNotNull()
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: {media_type}{CRLF}Content-Length: "), F.col("size").cast("string"), F.lit(CRLF * 2))
    block = F.when(is_revisit, http).otherwise(F.concat(http, "payload"))
    url = F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n]", " ")
    fields = [
        ("WARC-Type", F.when(is_revisit, "revisit").otherwise("response")),
        ("WARC-Record-ID", F.coalesce(F.col("key").cast("string"), F.lit("-"))),
        ("WARC-Target-URI", url),
        ("WARC-Payload-Digest", F.concat(F.lit("sha256:"), "digest")),
        ("WARC-Payload-Length", F.col("size").cast("string")),
        ("WARC-Refers-To", F.coalesce(F.col("refers_to").cast("string"), F.lit("-"))),
        ("Content-Type", F.lit("application/http; msgtype=response")),
        ("Content-Length", F.octet_length(block).cast("string")),
    ]
    head = [F.lit(MAGIC.decode())]
    for name, value in fields:
        head += [F.lit(f"{name}: "), value, F.lit(CRLF)]
    return F.concat(*head, F.lit(CRLF), block)


def write(pages: DataFrame, path: str, id_col: str = "page_id", url_col: str = "url", html_col: str = "html", *, least_bytes: int = 100, records_per_file: int = 2000) -> None:
    """Write one record for each row under ``path``."""
    records = mark_revisits(pages, id_col, url_col, html_col, least_bytes).select(record_text().alias("value"))
    records.write.option("lineSep", END.decode()).option("maxRecordsPerFile", records_per_file).text(path)


def candidates(content: bytes) -> list[tuple[int, int, dict[str, str], int]]:
    """(offset, successor, header fields, start of the block) of every place where a record could begin. A
    place whose header does not parse, or whose record does not end in a terminator, has no successor (-1)."""
    out = []
    for m in re.finditer(re.escape(MAGIC), content):
        close = content.find(END, m.end())
        head: dict[str, str] = {}
        if close >= 0:
            for line in content[m.end() : close].decode("utf-8", "replace").split(CRLF):
                name, colon, value = line.partition(": ")
                if colon:
                    head[name.lower()] = value
        length = head.get("content-length", "")
        begin = close + len(END)
        end = begin + int(length) if length.isdigit() else -1
        whole = end >= 0 and content[end : end + len(END)] == END
        out.append((m.start(), end + len(END) if whole else -1, head, begin))
    return out


def on_chain(offsets: np.ndarray, successors: np.ndarray) -> np.ndarray:
    """Which places the chain from offset 0 reaches, by pointer jumping over all places at once."""
    n = len(offsets)
    jump = np.full(n + 1, n, np.int64)
    at = np.searchsorted(offsets, successors)
    known = (at < n) & (successors > offsets)
    known[known] = offsets[at[known]] == successors[known]
    jump[:n][known] = at[known]
    reached = np.zeros(n + 1, bool)
    reached[0] = bool(n) and offsets[0] == 0
    while True:
        more = reached.copy()
        more[jump[reached]] = True
        jump = jump[jump]
        if (more == reached).all() and (jump == n).all():
            return reached[:n]
        reached = more


def read(spark, path: str, id_type: str = "long") -> DataFrame:
    """(key, url, payload_bytes, payload_digest, record_type, refers_to, html) of every record on the chain of
    each file under ``path``. Size and digest of a response are taken from the payload itself; those of a
    revisit, which carries no payload, from its header."""

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for blob in batch.column(0):
                yield records_of(blob.as_py())

    def records_of(content: bytes) -> pa.RecordBatch:
        places = candidates(content)
        kept = on_chain(np.array([p[0] for p in places], np.int64), np.array([p[1] for p in places], np.int64))
        rows: list[list] = [[] for _ in range(7)]
        for i in np.flatnonzero(kept):
            _, end, head, begin = places[i]
            if end < 0:
                continue
            kind = head.get("warc-type", "")
            if kind == "revisit":
                size, digest, html = int(head["warc-payload-length"]), head["warc-payload-digest"].removeprefix("sha256:"), None
            else:
                block = content[begin : end - len(END)]
                payload = block[block.find(END) + len(END) :]
                size, digest, html = len(payload), hashlib.sha256(payload).hexdigest(), payload.decode("utf-8", "replace")
            for column, value in zip(rows, (head["warc-record-id"], head["warc-target-uri"], size, digest, kind, head["warc-refers-to"], html)):
                column.append(value)
        types = [pa.string(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.string()]
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(rows, types)], ["k", "url", "payload_bytes", "payload_digest", "record_type", "r", "html"])

    files = spark.read.format("binaryFile").load(path).select("content")
    parsed = map_batches(files, parse, "k string, url string, payload_bytes long, payload_digest string, record_type string, r string, html string")
    ident = lambda c: F.when(F.col(c) != "-", F.col(c)).cast(id_type)
    return parsed.select(ident("k").alias("key"), "url", "payload_bytes", "payload_digest", "record_type", ident("r").alias("refers_to"), "html")
