"""WARC archives: writing with revisit records, and reading with boundary-chain verification.

Records are written by Spark's text writer, with the blank line that ends a record as its line
separator.  To read, tasks scan the files for the version line, which may as well stand inside a
payload, and emit for each place that parses as a record its successor's place.  Pointer jumping
from the start of each file then marks what the chain of records reaches; all else is payload.

Defined results: null html is an empty payload; control characters in a url are written as %20;
a null page_id stays null; equal rows of one page are records each; further columns are ignored;
an empty table gives an empty table.
"""

from __future__ import annotations

import re
from hashlib import sha1

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gradsift.llm.common import fresh_path, materialise, table

# Version line and header names of the format.
MAGIC = b"WARC/1.1\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Bytes of a file that the writer aims at; a task holds one file.
FILE_BYTES = 16 << 20
#: Payloads below this are always written in full.
REVISIT_BYTES = 1000
SALTS = 16
#: Repeated payloads whose digests are broadcast at most; beyond it the records are shuffled.
REPEATED = 200_000
HEADER = re.compile(rb"^([A-Za-z-]+):[ \t]*(.*)$")
CANDIDATE = "path string, size long, at long, next long, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long, uri string, payload binary"


def records(pages: DataFrame) -> DataFrame:
    """page_id, size, and the text of every record without the blank line that ends it."""
    p = pages.select(
        F.col("page_id").cast("long").alias("page_id"),
        F.regexp_replace(F.coalesce(F.col("url").cast("string"), F.lit("")), r"[\x00-\x20\x7F]", "%20").alias("url"),
        F.coalesce(F.col("html").cast("string"), F.lit("")).alias("payload"),
    )
    p = p.withColumn("size", F.octet_length("payload").cast("long")).withColumn("digest", F.sha1(F.col("payload").cast("binary")))
    again = p.where(F.col("size") >= REVISIT_BYTES).groupBy("digest").agg(F.max("page_id").alias("first_id"), F.count("*").alias("c")).where("c > 1").drop("c")
    again = materialise(again, "warc-again")
    if again.count() <= REPEATED:
        p = p.join(F.broadcast(again), "digest", "left")
    else:
        again = again.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        p = p.withColumn("salt", F.pmod(F.xxhash64("page_id"), F.lit(SALTS)).cast("int")).join(again, ["digest", "salt"], "left")
    revisit = F.col("first_id").isNotNull() & ~F.col("first_id").eqNullSafe(F.col("page_id"))
    urn = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("none")), F.lit(">"))
    line = lambda name, c: F.concat(F.lit(f"{name}: "), c, F.lit("\r\n"))
    head = F.concat(
        F.lit(MAGIC.decode()),
        line("WARC-Type", F.when(revisit, "revisit").otherwise("response")),
        line("WARC-Record-ID", urn(F.col("page_id"))),
        line("WARC-Date", F.lit("1970-01-01T00:00:00Z")),
        line("WARC-Target-URI", F.col("url")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        line("WARC-Payload-Length", F.col("size").cast("string")),
        F.when(revisit, F.concat(line("WARC-Refers-To", urn(F.col("first_id"))), line("WARC-Profile", F.lit(PROFILE)))).otherwise(F.lit("")),
        line("Content-Type", F.lit("text/html; charset=utf-8")),
        F.lit("Content-Length: "),
        F.when(revisit, F.lit("0")).otherwise(F.col("size").cast("string")),
    )
    return p.select("page_id", "size", F.concat(head, F.lit("\r\n\r\n"), F.when(revisit, F.lit("")).otherwise(F.col("payload"))).alias("value"))


def write_archives(pages: DataFrame, path: str, file_bytes: int = FILE_BYTES) -> None:
    """Files of about ``file_bytes`` or less, written where the join left the records."""
    n, total = pages.agg(F.count("*"), F.sum(F.coalesce(F.octet_length("html"), F.lit(0)) + 400)).first()
    most = max(1, file_bytes * n // max(total or 0, 1))
    out = records(pages).select("value").write.option("maxRecordsPerFile", most)
    out.option("lineSep", "\r\n\r\n").option("compression", "none").text(path)


def _number(header: dict[bytes, bytes], name: bytes) -> int | None:
    m = re.fullmatch(rb"<urn:page:(-?\d+)>", header.get(name, b""))
    return int(m[1]) if m else None


def candidates(data: bytes, with_payload: bool = False):
    """Every place that parses as a record, with the place of its successor."""
    at = data.find(MAGIC)
    while at >= 0:
        end = data.find(b"\r\n\r\n", at)
        if end < 0:
            return
        lines = data[at + len(MAGIC) : end].split(b"\r\n")
        header = {m[1].lower(): m[2] for x in lines if (m := HEADER.match(x))}
        size = header.get(b"content-length", b"")
        if len(header) == len(lines) and size.isdigit():
            begin, stop = end + 4, end + 4 + int(size)
            if data[stop : stop + 4] == b"\r\n\r\n":
                payload = data[begin:stop]
                kind = header.get(b"warc-type", b"").decode("ascii", "replace")
                if kind == "revisit":
                    length, digest = header.get(b"warc-payload-length", b"0"), header.get(b"warc-payload-digest", b"").removeprefix(b"sha1:").decode("ascii", "replace")
                    length = int(length) if length.isdigit() else 0
                else:
                    length, digest = len(payload), sha1(payload).hexdigest()
                uri = header.get(b"warc-target-uri", b"").decode("utf-8", "replace")
                yield at, stop + 4, _number(header, b"warc-record-id"), length, digest, kind, _number(header, b"warc-refers-to"), uri, payload if with_payload else None
        at = data.find(MAGIC, at + 1)


def reachable(at: np.ndarray, following: np.ndarray) -> np.ndarray:
    """Which of the ascending places the chain from place 0 reaches, by pointer jumping."""
    n = len(at)
    seen = np.zeros(n + 1, bool)
    if n and at[0] == 0:
        seen[0] = True
    jump = np.searchsorted(at, following)
    jump = np.append(np.where((jump < n) & (at[np.minimum(jump, n - 1)] == following), jump, n), n) if n else np.zeros(1, np.int64)
    step = 1
    while step <= n:
        seen[jump[seen]] = True
        jump = jump[jump]
        step *= 2
    return seen[:n]


def read_archives(spark: SparkSession, path: str, with_payload: bool = False) -> DataFrame:
    """One row per verified record of the files below ``path``."""

    def scan(batches):
        for b in batches:
            for name, data in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                data = data.as_py()
                cols = list(zip(*candidates(data, with_payload), strict=True)) or [()] * 9
                n = len(cols[0])
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string(), pa.binary()]
                yield pa.RecordBatch.from_arrays([pa.array([name] * n, pa.string()), pa.array([len(data)] * n, pa.int64()), *(pa.array(c, k) for c, k in zip(cols, kinds, strict=True))], [x.split()[0] for x in CANDIDATE.split(", ")])

    def chain(t: pa.Table) -> pa.Table:
        t = t.sort_by("at")
        return t.filter(pa.array(reachable(t.column("at").to_numpy(), t.column("next").to_numpy())))

    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "content")
    return files.mapInArrow(scan, CANDIDATE).groupBy("path").applyInArrow(chain, CANDIDATE)


def op7_boundary_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages written to archives and read back."""
    path = fresh_path(spark, "warc")
    write_archives(table(spark, sf_dir, "pages"), path)
    return read_archives(spark, path).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP7_SQL = """
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS d FROM pages
), g AS (
  SELECT d, max(page_id) AS m FROM p WHERE n >= 1000 GROUP BY d
)
SELECT p.page_id, p.n::BIGINT AS payload_bytes, p.d AS payload_digest,
  CASE WHEN g.m IS NULL OR g.m = p.page_id THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN g.m <> p.page_id THEN g.m END AS refers_to
FROM p LEFT JOIN g ON p.d = g.d AND p.n >= 1000
"""
