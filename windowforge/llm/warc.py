"""WARC archives of web pages: written as whole-file gzip streams, normalised to one gzip member a record, read back by offset."""

from __future__ import annotations

import base64
import hashlib
import io
import json
import re
import uuid
import zlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh_path, materialize, ship

#: Fixed values of the formats.
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
END = "\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8" + END

READ, LEVEL = 1 << 20, 6
FIELDS = "page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"


def sha1_base32(payload: Column) -> Column:
    """Bare upper-case base32 of the SHA-1: 40 hex digits, five of which make four letters."""
    digest = F.sha1(payload)
    out = []
    for k in range(8):
        v = F.conv(F.substring(digest, 5 * k + 1, 5), 16, 10).cast("int")
        out += [F.substr(F.lit(BASE32), F.shiftright(v, 15 - 5 * j).bitwiseAND(31) + 1, F.lit(1)) for j in range(4)]
    return F.concat(*out)


def records(pages: DataFrame, dedup_bytes: int = 0) -> DataFrame:
    """One WARC record per row as text, without its closing blank lines; payloads of at least ``dedup_bytes`` that an
    earlier page_id holds too become revisits.

    Only ids and digests meet to find the earlier page; they are folded before the shuffle. Null html is an empty
    payload; a very long one is one record, which its row holds whole. Rows that share page_id and payload are all responses if no smaller page_id holds it, else all revisits.
    A row without a page_id is a response.
    """
    payload = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    rows = pages.select("page_id", F.regexp_replace(F.coalesce("url", F.lit("urn:no-url")), r"[\x00-\x20\x7f]", "%20").alias("uri"), F.coalesce("html", F.lit("")).alias("html"), F.unhex(F.sha2(payload, 256)).alias("sha"), F.length(payload).cast("long").alias("n"))
    narrow = rows.filter(F.col("n") >= dedup_bytes).select("page_id", "sha")
    first = narrow.groupBy("sha").agg(F.min("page_id").alias("first"), F.count(F.lit(1)).alias("copies")).filter("copies > 1")
    later = narrow.join(first, "sha").filter("page_id > first").select("page_id", "sha", "first").distinct()
    urn = lambda c: F.concat(F.lit("<urn:x-page:"), F.coalesce(c.cast("string"), F.lit("none")), F.lit(">"))
    body = F.encode("html", "UTF-8")
    head = lambda *lines: F.concat_ws("\r\n", F.lit("WARC/1.1"), *lines)
    field = lambda name, value: F.concat(F.lit(f"{name}: "), value)
    shared = [
        field("WARC-Record-ID", urn(F.col("page_id"))),
        F.lit("WARC-Date: 2026-01-01T00:00:00Z"),
        field("WARC-Target-URI", F.col("uri")),
        field("WARC-Payload-Digest", F.concat(F.lit("sha1:"), sha1_base32(body))),
        field("X-Payload-Length", F.col("n").cast("string")),
        F.lit("Content-Type: application/http;msgtype=response"),
    ]
    response = F.concat(head(F.lit("WARC-Type: response"), *shared, field("Content-Length", (F.col("n") + len(HTTP)).cast("string"))), F.lit(END + HTTP), F.col("html"))
    revisit = F.concat(head(F.lit("WARC-Type: revisit"), *shared, F.lit(f"WARC-Profile: {PROFILE}"), field("WARC-Refers-To", urn(F.col("first"))), F.lit(f"Content-Length: {len(HTTP)}")), F.lit(END + HTTP))
    return rows.join(later, ["page_id", "sha"], "left").select(F.when(F.col("first").isNull(), response).otherwise(revisit).alias("value"))


def write_archives(pages: DataFrame, path: str, dedup_bytes: int = 0, per_file: int = 20_000) -> None:
    """Archives as most crawlers' exports come: each file one gzip stream over all its records. Spark's own commit makes the files appear whole or not at all."""
    records(pages, dedup_bytes).write.option("lineSep", END).option("maxRecordsPerFile", per_file).option("compression", "gzip").text(path)


def file_system(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(re.sub(r"^file:/+", "file:///", uri))


def inflated(source, most: int = READ) -> Iterator[bytes]:
    """The bytes under a gzip file, at most ``most`` at once, through as many members as it has; zero bytes between and behind members are padding."""
    inflate, fed = zlib.decompressobj(31), False
    while block := source.read(READ):
        more = True
        while more:
            if not fed:
                block = block.lstrip(b"\0")
                if not block:
                    break
            data = inflate.decompress(block, most)
            fed = True
            if data:
                yield data
            if inflate.eof:
                block, inflate, fed = inflate.unused_data, zlib.decompressobj(31), False
                more = bool(block)
            else:
                block = inflate.unconsumed_tail
                more = bool(block) or len(data) == most
    if fed:
        raise ValueError("the gzip stream ends early")


def parse_head(head: bytes) -> dict[str, str]:
    first, *lines = head.decode("utf-8", "replace").split("\r\n")
    if not first.startswith("WARC/"):
        raise ValueError(f"no WARC record begins with {first[:40]!r}")
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines)}


def split_records(blocks: Iterator[bytes]) -> Iterator[tuple[dict[str, str], bytes]]:
    """(fields, whole record with its closing blank lines) from a stream; holds one record and one block at a time."""
    held = bytearray()

    def want(n: int) -> bool:
        while len(held) < n:
            more = next(blocks, None)
            if more is None:
                return False
            held.extend(more)
        return True

    while want(1):
        while (cut := held.find(END.encode())) < 0:
            if not want(len(held) + 1):
                raise ValueError("a record has no end of its head")
        fields = parse_head(bytes(held[:cut]))
        size = cut + 4 + int(fields["content-length"])
        if not want(size + 4) and len(held) < size:
            raise ValueError("a record ends early")
        yield fields, bytes(held[:size]) + END.encode()
        del held[: size + 4]


def normalise_archive(source_uri: str, target_uri: str) -> tuple[int, int]:
    """Rewrites one archive with a gzip member a record and a sidecar of offsets beside it; returns records and bytes.

    Both files get their names only when complete, and the same source always gives the same bytes, so a task that runs
    again after a lost executor, or twice at once, does no harm.
    """
    (fs_in, path_in), (fs_out, path_out) = file_system(source_uri), file_system(target_uri)
    fs_out.create_dir(path_out.rsplit("/", 1)[0], recursive=True)
    mark, at, n = f".{uuid.uuid4().hex}.tmp", 0, 0
    with fs_in.open_input_stream(path_in, compression=None) as source, fs_out.open_output_stream(path_out + mark, compression=None) as out, fs_out.open_output_stream(f"{path_out}.idx{mark}", compression=None) as index:
        for fields, record in split_records(inflated(source)):
            pack = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
            member = pack.compress(record) + pack.flush()
            out.write(member)
            entry = {"offset": at, "length": len(member), "type": fields["warc-type"], "id": fields["warc-record-id"], "uri": fields.get("warc-target-uri"), "digest": fields.get("warc-payload-digest")}
            index.write((json.dumps(entry, ensure_ascii=False) + "\n").encode())
            at, n = at + len(member), n + 1
    fs_out.move(f"{path_out}.idx{mark}", f"{path_out}.idx")
    fs_out.move(path_out + mark, path_out)
    return n, at


def normalise(spark, source_dir: str, target_dir: str) -> DataFrame:
    """All archives of a folder, one task each; rows (archive, records, bytes). The rows are written down, so the work is done once."""
    ship(spark)
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.gz").load(source_dir).select("path")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for path in batch["path"]:
                name = re.sub(r"(\.txt|\.warc)?\.gz$", ".warc.gz", path.rsplit("/", 1)[1])
                target = f"{target_dir}/{name}"
                yield pd.DataFrame([(target, *normalise_archive(path, target))], columns=["archive", "records", "bytes"])

    return materialize(files.repartition(spark.sparkContext.defaultParallelism * 4, "path").mapInPandas(run, "archive string, records long, bytes long"), "warc-manifest")


def page_of(urn: str | None) -> int | None:
    found = re.fullmatch(r"<urn:x-page:(-?\d+)>", urn or "")
    return int(found[1]) if found else None


def read_record(member: bytes) -> tuple[dict[str, str], bytes]:
    """Fields and payload of one gzip member; the payload is checked against its digest."""
    ((fields, record),) = split_records(inflated(io.BytesIO(member)))
    block = record[record.index(END.encode()) + 4 : -4]
    payload = block[block.index(END.encode()) + 4 :]
    if fields["warc-type"] == "response" and fields["warc-payload-digest"] != "sha1:" + base64.b32encode(hashlib.sha1(payload).digest()).decode():
        raise ValueError(f"{fields['warc-record-id']}: payload and digest differ")
    return fields, payload


def read_back(manifest: DataFrame) -> DataFrame:
    """A row per record, found through the sidecars: each record is sought, read and inflated by itself."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for archive in batch["archive"]:
                fs, path = file_system(archive)
                rows = []
                with fs.open_input_stream(path + ".idx", compression=None) as index, fs.open_input_file(path) as data:
                    for line in io.TextIOWrapper(io.BufferedReader(index), encoding="utf-8", newline="\n"):
                        entry = json.loads(line)
                        data.seek(entry["offset"])
                        fields, payload = read_record(data.read(entry["length"]))
                        whole = fields["warc-type"] == "response"
                        rows.append((page_of(fields["warc-record-id"]), len(payload) if whole else int(fields["x-payload-length"]), fields["warc-payload-digest"].removeprefix("sha1:"), fields["warc-type"], page_of(fields.get("warc-refers-to"))))
                        if len(rows) == 5000:
                            yield frame(rows)
                            rows = []
                if rows:
                    yield frame(rows)

    def frame(rows: list[tuple]) -> pd.DataFrame:
        ids, sizes, digests, kinds, refers = zip(*rows)
        return pd.DataFrame({"page_id": pd.array(ids, dtype="Int64"), "payload_bytes": list(sizes), "payload_digest": list(digests), "record_type": list(kinds), "refers_to": pd.array(refers, dtype="Int64")})

    spark = manifest.sparkSession
    return manifest.repartition(spark.sparkContext.defaultParallelism * 4, "archive").mapInPandas(run, FIELDS)


def warc_round_trip(pages: DataFrame, dedup_bytes: int = 0) -> DataFrame:
    """Pages written to archives, normalised and read back; a row per page with what its record says.

    Needs page_id, url and html; further columns are left alone. A very long payload is held whole, a record at a time, and
    never inflated past a block at once. Revisits keep the digest and the length that their page had when it was written. Repeated
    rows are records each. An empty table gives an empty result.
    """
    spark = pages.sparkSession
    raw, done = fresh_path(spark, "warc-raw"), fresh_path(spark, "warc-members")
    write_archives(pages, raw, dedup_bytes)
    return read_back(normalise(spark, raw, done))
