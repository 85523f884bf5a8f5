"""Web archives: writing captures with revisits, reading archives, and assembling transactions.

Each capture is three records, a request, a response (or a revisit of an equal payload) and a metadata record;
request and metadata name the response by ``WARC-Concurrent-To``. Archives are written by Spark's text
writer, a record a row with the format's own record end as row end, and gzip; they are read as whole files
and cut by Content-Length, never by looking for marks inside payloads. ``assemble`` groups records by the
identifier they are concurrent to and emits one nested row per capture.

Defined results: every row is a capture, repeated rows and rows of equal page_id too (an ordinal in their record
identifiers tells them apart); null html is an empty payload; null url gives no target; a null page_id is written
as such and read back as null, and is never the page that others revisit; other columns are ignored; an empty table
gives an empty result; very long pages go to files of few records, so a file stays below the size that can be
read as one cell. Records of which a part is missing still give a row, that part null.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relseq.llm import store

DATE = "2024-01-01T00:00:00Z"
LEAST_SHARED = 100
FILE_BYTES = 192 << 20  # of payloads, at most, unless a single one has more
LEAST_CLASS, MOST_RECORDS = 16, 3000  # payloads up to 64 KB go 1000 to a file, each with its three records
BROADCAST_DIGESTS = 100_000
AGAIN = 1000  # repeated rows written from one row of the plan
END = "\r\n\r\n"
RECORD = "record_id string, type string, concurrent_to string, refers_to string, target string, payload_bytes long, payload_digest string, fields map<string,string>"


def revisit_plan(pages: DataFrame, least: int = LEAST_SHARED) -> DataFrame:
    """page_id, url, html, n, digest, u, ordinal, first, first_u: a capture a row. ``first`` is the page of the response
    with an equal payload, or null; ``u`` names the url, and ``ordinal`` counts rows that are equal in everything."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce("html", F.lit("")).alias("html"))
    rows = rows.select("*", F.octet_length("html").cast("long").alias("n"), F.sha2("html", 256).alias("digest"), F.hex(F.xxhash64("url")).alias("u"))
    keys = rows.groupBy("digest", "n", "page_id", "u").agg(F.count("*").alias("m"))
    leader = F.min(F.when(F.col("page_id").isNotNull() & (F.col("n") >= least), F.struct("page_id", "u")))
    shared = keys.groupBy("digest").agg(leader.alias("leader"), F.count("*").alias("k"), F.max("m").alias("m")).where("k > 1 or m > 1").drop("k")
    shared = store.materialise(shared, "shared")
    joined = rows.join(shared, "digest", "left")
    once = joined.where("m is null or m = 1").withColumn("ordinal", F.lit(0).cast("long"))
    repeated = shared.where("m > 1")
    several = repeated.count()
    if not several:
        return _led(once)
    # Rows equal in everything are folded before they are exchanged, and written out again in portions.
    same = ["page_id", "u", "digest"]
    pages_again = rows.join(F.broadcast(repeated) if several <= BROADCAST_DIGESTS else repeated, "digest")
    folded = pages_again.groupBy(*same).agg(*[F.first(c).alias(c) for c in ("url", "html", "n", "leader")], F.count("*").alias("m"))
    portions = folded.withColumn("at", F.explode(F.expr(f"sequence(0L, (m - 1) div {AGAIN})"))).hint("rebalance")
    again = portions.withColumn("ordinal", F.explode(F.expr(f"sequence(at * {AGAIN}, least(m, (at + 1) * {AGAIN}) - 1)"))).drop("at")
    return _led(once.unionByName(again.select(*once.columns)))


def _led(every: DataFrame) -> DataFrame:
    leads = F.col("page_id").eqNullSafe(F.col("leader.page_id"))
    return every.withColumn("first", F.when(~leads, F.col("leader.page_id"))).withColumn("first_u", F.when(~leads, F.col("leader.u"))).drop("leader", "m")


def _record(kind: str, name, extra: list, content_type: str, block):
    lines = [F.lit(f"WARC/1.1\r\nWARC-Type: {kind}\r\nWARC-Date: {DATE}\r\nWARC-Record-ID: "), name, *extra]
    lines += [F.lit(f"\r\nContent-Type: {content_type}\r\nContent-Length: "), F.octet_length(block).cast("string"), F.lit("\r\n\r\n"), block]
    return F.concat(*lines)


def records(planned: DataFrame) -> DataFrame:
    """One column of record texts, three rows a capture."""

    def name(kind, page=F.col("page_id"), u=F.col("u"), ordinal=F.col("ordinal")):
        return F.concat(F.lit("<urn:capture:"), F.coalesce(page.cast("string"), F.lit("null")), F.lit(":"), F.substring("digest", 1, 16), F.lit(":"), u, F.lit(":"), ordinal.cast("string"), F.lit(f":{kind}>"))

    own = name("response")
    target = F.coalesce(F.concat(F.lit("\r\nWARC-Target-URI: "), F.regexp_replace("url", "[\\r\\n]", "")), F.lit(""))
    also = F.concat(F.lit("\r\nWARC-Concurrent-To: "), own)
    digest = F.concat(F.lit("\r\nWARC-Payload-Digest: sha256:"), F.col("digest"))
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("n").cast("string"), F.lit("\r\n\r\n"))
    ask = F.concat(F.lit("GET "), F.coalesce(F.regexp_replace("url", "[\\r\\n ]", ""), F.lit("/")), F.lit(" HTTP/1.1\r\n\r\n"))
    about = F.concat(F.lit("page: "), F.coalesce(F.col("page_id").cast("string"), F.lit("")), F.lit("\r\npayload-bytes: "), F.col("n").cast("string"), F.lit("\r\n"))
    response = _record("response", own, [target, digest], "application/http; msgtype=response", F.concat(http, F.col("html")))
    profile = F.lit("\r\nWARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")
    revisit = _record("revisit", own, [target, digest, profile, F.concat(F.lit("\r\nWARC-Refers-To: "), name("response", F.col("first"), F.col("first_u"), F.lit(0)))], "application/http; msgtype=response", http)
    request = _record("request", name("request"), [target, also], "application/http; msgtype=request", ask)
    metadata = _record("metadata", name("metadata"), [target, also], "application/warc-fields", about)
    three = F.array(request, F.when(F.col("first").isNull(), response).otherwise(revisit), metadata)
    return planned.select(F.explode(three).alias("value"))


def write_archives(pages: DataFrame, path: str) -> None:
    """Files of bounded size: payloads of about the same size stand together, the larger the fewer in a file."""
    log_size = F.greatest(F.lit(LEAST_CLASS), F.ceil(F.log2(F.greatest(F.octet_length(F.coalesce("html", F.lit(""))), F.lit(1)))))
    classes = [r["c"] for r in pages.select(log_size.alias("c")).distinct().collect()]  # at most 16 rows: a text has less than 2 GB
    planned = revisit_plan(pages)
    for c in sorted(classes) or [LEAST_CLASS]:
        log_n = F.greatest(F.lit(LEAST_CLASS), F.ceil(F.log2(F.greatest("n", F.lit(1)))))
        most = min(MOST_RECORDS, 3 * max(1, FILE_BYTES >> c))
        records(planned.where(log_n == c)).write.option("lineSep", END).option("compression", "gzip").option("maxRecordsPerFile", most).text(f"{path}/size={c}")


def parse(chunks: Iterator[bytes]) -> Iterator[tuple]:
    """Records of one archive given in pieces; holds one record at a time."""
    held = bytearray()
    chunks = iter(chunks)

    def fill(n: int) -> bool:
        while len(held) < n:
            more = next(chunks, None)
            if more is None:
                return False
            held.extend(more)
        return True

    while True:
        while (head := held.find(b"\r\n\r\n")) < 0:
            if not fill(len(held) + 1):
                if held.strip():
                    raise ValueError("an archive ends inside a record's header")
                return
        lines = bytes(held[:head]).decode("utf-8", "replace").split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"not a record: {lines[0][:40]!r}")
        fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
        size = int(fields["content-length"])
        if not fill(head + 4 + size):
            raise ValueError("an archive ends inside a record")
        block = bytes(held[head + 4 : head + 4 + size])
        fill(head + 8 + size)
        del held[: head + 8 + size]
        kind = fields.get("warc-type", "")
        payload, extra = block, {}
        if fields.get("content-type", "").startswith("application/http"):
            _, _, payload = block.partition(b"\r\n\r\n")
        elif fields.get("content-type") == "application/warc-fields":
            extra = {k.strip(): v.strip() for k, _, v in (x.partition(":") for x in block.decode("utf-8", "replace").split("\r\n") if x)}
        digest = hashlib.sha256(payload).hexdigest()
        given = fields.get("warc-payload-digest", "").rpartition(":")[2] or None
        if kind == "response" and given and given != digest:
            raise ValueError(f"a payload does not have its digest: {fields.get('warc-record-id')}")
        yield (fields.get("warc-record-id"), kind, fields.get("warc-concurrent-to"), fields.get("warc-refers-to"), fields.get("warc-target-uri"), len(payload), given if kind == "revisit" else digest, extra)


def _gunzip(data: bytes, size: int = 1 << 20) -> Iterator[bytes]:
    """Pieces of a gzip file of any number of members."""
    if data[:2] != b"\x1f\x8b":
        yield data
        return
    left = data
    while left:
        z = zlib.decompressobj(31)
        while not z.eof:
            piece = z.decompress(left, size)
            left = z.unconsumed_tail or z.unused_data
            if piece:
                yield piece
            elif not left and not z.eof:
                raise ValueError("a gzip member ends early")


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        types = [pa.string()] * 5 + [pa.int64(), pa.string(), pa.map_(pa.string(), pa.string())]
        names = [x.strip().split(" ")[0] for x in RECORD.replace("map<string,string>", "map").split(",")]
        for batch in batches:
            for cell in batch.column(0):
                held = []
                for row in parse(_gunzip(cell.as_buffer().to_pybytes())):
                    held.append((*row[:-1], list(row[-1].items())))
                    if len(held) >= 2000:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held), types)], names)
                        held = []
                if held:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*held), types)], names)

    return spark.read.format("binaryFile").load(path).select("content").mapInArrow(run, RECORD)


def assemble(found: DataFrame) -> DataFrame:
    """(capture, request, response, metadata): records joined through the identifier they are concurrent to.

    A capture has a handful of records, and each is folded into its part before the exchange.
    """
    whole = F.struct("record_id", "type", "refers_to", "target", "payload_bytes", "payload_digest")
    main = F.col("type").isin("response", "revisit")
    capture = F.when(main, F.col("record_id")).otherwise(F.coalesce("concurrent_to", "record_id"))
    extra = F.to_json("fields")
    parts = found.select(capture.alias("capture"), F.when(main, whole).alias("m"), F.when(F.col("type") == "request", whole).alias("q"), F.when(F.col("type") == "metadata", F.struct("record_id", extra.alias("fields"))).alias("d"))
    grouped = parts.groupBy("capture").agg(F.max("q").alias("request"), F.max("m").alias("response"), F.max("d").alias("metadata"))
    return grouped.withColumn("metadata", F.struct("metadata.record_id", F.from_json("metadata.fields", "map<string,string>").alias("fields")))


def _page(name):
    return F.regexp_extract(name, r"^<urn:capture:(-?\d+):", 1).try_cast("long")


def captures(assembled: DataFrame) -> DataFrame:
    """A row for each capture that has a response or revisit; a revisit's size stands in its metadata."""
    r = F.col("response")
    revisit = r["type"] == "revisit"
    size = F.when(revisit, F.col("metadata.fields")["payload-bytes"].cast("long")).otherwise(r["payload_bytes"])
    return assembled.where(r.isNotNull()).select(_page(r["record_id"]).alias("page_id"), size.alias("payload_bytes"), r["payload_digest"].alias("payload_digest"), r["type"].alias("record_type"), F.when(revisit, _page(r["refers_to"])).alias("refers_to"), r["target"].alias("url"))


def op3_warc_transactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = store.new_path(spark, "warc")
    write_archives(store.table(spark, sf_dir, "pages"), path)
    return captures(assemble(read_archives(spark, path)))


OP3_SQL = """
with p as (select page_id, url, octet_length(encode(coalesce(html, ''))) n, sha256(coalesce(html, '')) digest from pages),
f as (select *, min(page_id) over (partition by digest) first from p)
select page_id, n::bigint payload_bytes, digest payload_digest,
       case when n >= 100 and page_id <> first then 'revisit' else 'response' end record_type,
       case when n >= 100 and page_id <> first then first end refers_to, url from f
"""
