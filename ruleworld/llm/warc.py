"""Deterministic, sharded WARC archives: writer, manifest and reader.

Records are range-sorted by page id, digest and url. Each task writes its range as gzip members, one a record, and starts
the next file when the compressed size passes a limit. Headers, record ids and digests are made anew from what a row
holds (page id, digest of payload and url, and a number among rows that are equal in all of these), with a fixed date, so that
any attempt of a task, and any layout of the table, writes the same records; files are written under temporary names
and renamed, and the manifest lists what counts. Of records with equal payloads of a least size one is a response and
the others are revisits that name it. What tells so travels without payloads: digests are grouped with partial
aggregation, and rows whose digest is surely alone (by a bitmap of bounded size) are in no join.

Edge cases: a null html is an empty payload, null urls an empty target; a null id sorts first and is a response before
no other id; repeated rows are records of their own, one of which is the response; very long pages are one record;
further columns are ignored, whatever their names; no rows give no files.
"""

from __future__ import annotations

import gzip
import hashlib
import zlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ruleworld.llm.sift import bitmap, maybe_in, numbered
from ruleworld.llm.store import Store
from ruleworld.operators.rank import running_total
from ruleworld.sources.scratch import settle, shared_dir

MANIFEST = "file string, records bigint, bytes bigint, sha256 string, first_id bigint, last_id bigint"
EPOCH = "1970-01-01T00:00:00Z"
#: Fixed value: the profile of revisits with the same payload.
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n"


def record_id(page: int | None, mark: str, place: int) -> str:
    """URI of a record; ``mark``, a hash of payload and url, and ``place`` among equal rows keep repeated and null ids apart."""
    return f"<urn:page:{'none' if page is None else page}:{mark}:{place}>"


def page_of(uri: str) -> int | None:
    part = uri.strip("<>").split(":")[2]
    return None if part == "none" else int(part)


def build_record(page: int | None, mark: str, place: int, url: str | None, payload: bytes, digest: str, refers: tuple[int | None, str, int] | None, date: str = EPOCH) -> bytes:
    """One record, uncompressed. A revisit has the HTTP head only; its payload's length and digest stay in its headers."""
    block = HTTP % len(payload) + (b"" if refers else payload)
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if refers else 'response'}",
        f"WARC-Record-ID: {record_id(page, mark, place)}",
        f"WARC-Target-URI: {(url or '').replace(chr(13), '%0D').replace(chr(10), '%0A')}",
        f"WARC-Date: {date}",
        f"WARC-Payload-Digest: sha256:{digest}",
        f"WARC-Block-Digest: sha256:{hashlib.sha256(block).hexdigest()}",
    ]
    if refers:
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(*refers)}"]
    head += [f"X-Payload-Length: {len(payload)}", "Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode("utf-8", "surrogatepass") + b"\r\n\r\n" + block + b"\r\n\r\n"


def parse_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Headers and payload of a record; digests and lengths are verified."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    version, *lines = head.decode("utf-8", "surrogatepass").split("\r\n")
    headers = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in lines)
    block = rest[: int(headers["Content-Length"])]
    if version != "WARC/1.1" or rest[len(block) :] != b"\r\n\r\n" or "sha256:" + hashlib.sha256(block).hexdigest() != headers["WARC-Block-Digest"]:
        raise ValueError(f"record {headers.get('WARC-Record-ID')} is damaged")
    payload = block.partition(b"\r\n\r\n")[2]
    if headers["WARC-Type"] == "response" and ("sha256:" + hashlib.sha256(payload).hexdigest() != headers["WARC-Payload-Digest"] or len(payload) != int(headers["X-Payload-Length"])):
        raise ValueError(f"payload of {headers['WARC-Record-ID']} is damaged")
    return headers, payload


def members(f, size: int = 1 << 20):
    """Decompressed gzip members of a stream, one at a time."""
    unpack, out, left = zlib.decompressobj(31), [], b""
    while data := left or f.read(size):
        out.append(unpack.decompress(data))
        left = unpack.unused_data
        if unpack.eof:
            yield b"".join(out)
            unpack, out = zlib.decompressobj(31), []
        else:
            left = b""
    if any(out):
        raise ValueError("an archive ends inside a record")


def _writing(where: str, roll: int, date: str):
    def write(batches):
        from pyspark import TaskContext

        part, store, made = TaskContext.get().partitionId(), Store(where), []
        out = None

        def close():
            nonlocal out
            store.commit(out)
            made.append((name, records, size, check.hexdigest(), first, last))
            out = None

        for b in batches:
            for page, mark, place, url, html, digest, to, to_mark, to_place in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if out is None:
                    name = f"part-{part:06d}-{len(made):05d}.warc.gz"
                    out, records, size, check, first = store.create(name), 0, 0, hashlib.sha256(), page
                refers = None if to_place is None else (to, to_mark, to_place)
                raw = gzip.compress(build_record(page, mark, place, url, (html or "").encode("utf-8", "surrogatepass"), digest, refers, date), 6, mtime=0)
                out.write(raw)
                check.update(raw)
                records, size, last = records + 1, size + len(raw), page
                if size >= roll:
                    close()
        if out is not None:
            close()
        if made:
            yield pa.RecordBatch.from_arrays([pa.array(c) if k not in (4, 5) else pa.array(c, pa.int64()) for k, c in enumerate(zip(*made, strict=True))], names=[x.split()[0] for x in MANIFEST.split(", ")])

    return write


SORT = ["page_id", "digest", "url"]


def _numbered_ties(slim: DataFrame) -> DataFrame:
    """``rid, place``: numbers from 0 among rows of equal id, digest and url, for those that have such others."""
    ties = slim.groupBy(*SORT).agg(F.count("*").alias("n")).filter("n > 1").select(*[F.col(c).alias(f"t_{c}") for c in SORT])
    same = [F.col(c).eqNullSafe(F.col(f"t_{c}")) for c in SORT]
    tied = slim.join(ties, same, "left_semi")
    return running_total(tied, [*SORT, "rid"], F.lit(1).cast("long"), "place", within=SORT).select("rid", (F.col("place") - 1).alias("place"))


def mark_revisits(pages: DataFrame, least: int = 100, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """``page_id, mark, place, url, html, digest, to, to_mark, to_place``: the last three name the response of a revisit."""
    rows = numbered(pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html")), "rid")
    rows = rows.withColumn("digest", F.sha2(F.coalesce("html", F.lit("")), 256))
    rows = rows.withColumn("mark", F.substring(F.sha2(F.concat_ws("\n", "digest", "url"), 256), 1, 16))
    large = F.octet_length(F.coalesce("html", F.lit(""))) >= least
    slim = settle(rows.select("rid", *SORT, "mark", large.alias("large")))
    ties = settle(_numbered_ties(slim))
    slim = slim.join(ties, "rid", "left").withColumn("place", F.coalesce("place", F.lit(0).cast("long")))
    order = F.struct(F.col("page_id").isNull().alias("a"), F.col("page_id").alias("b"), F.col("mark").alias("c"), F.col("place").alias("d"))
    several = slim.filter("large").groupBy("digest").agg(F.min(order).alias("best"), F.count("*").alias("n")).filter("n > 1")
    several = settle(several.select("digest", F.col("best.b").alias("to"), F.col("best.c").alias("to_mark"), F.col("best.d").alias("to_place")))
    # rows that may be tied or revisits meet what is known of them by number; all others stay out of the join
    response = (F.col("page_id").eqNullSafe(F.col("to"))) & (F.col("mark") == F.col("to_mark")) & (F.col("place") == F.col("to_place"))
    known = slim.join(several, "digest", "left").select("rid", "place", *[F.when(~response, F.col(c)).alias(c) for c in ("to", "to_mark", "to_place")])
    known = settle(known.filter("place > 0 OR to_mark IS NOT NULL"))
    bits, words = bitmap(known, "rid", known.count())
    held = maybe_in(bits, words, F.col("rid"))
    alone = rows.filter(~held).select("*", F.lit(0).cast("long").alias("place"), *[F.lit(None).cast(t).alias(c) for c, t in (("to", "long"), ("to_mark", "string"), ("to_place", "long"))])
    met = rows.filter(held).join(known, "rid", "left").withColumn("place", F.coalesce("place", F.lit(0).cast("long")))
    names = ["page_id", "mark", "place", "url", "html", "digest", "to", "to_mark", "to_place"]
    return alone.select(*names).unionByName(met.select(*names))


def write_archives(pages: DataFrame, least: int = 100, roll: int = 64 << 20, date: str = EPOCH, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> tuple[str, DataFrame]:
    """Folder of the archives, and their manifest (written beside them)."""
    where = shared_dir(pages.sparkSession)
    rows = mark_revisits(pages, least, id_col, url_col, html_col).repartitionByRange(*SORT, "place").sortWithinPartitions(*SORT, "place")
    return where, settle(rows.mapInArrow(_writing(where, roll, date), MANIFEST))


READ = "page_id bigint, url string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint, html string"


def _reading(where: str, payloads: bool):
    def read(batches):
        store = Store(where)
        for b in batches:
            for name, digest in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                check, rows = hashlib.sha256(), []
                with store.open(name) as f:
                    for raw in members(_Tee(f, check)):
                        h, payload = parse_record(raw)
                        refers = h.get("WARC-Refers-To")
                        rows.append((page_of(h["WARC-Record-ID"]), h["WARC-Target-URI"], int(h["X-Payload-Length"]), h["WARC-Payload-Digest"][7:], h["WARC-Type"], page_of(refers) if refers else None, payload.decode("utf-8", "surrogatepass") if payloads and not refers else None))
                        if len(rows) == 500:
                            yield _read_batch(rows)
                            rows = []
                if check.hexdigest() != digest:
                    raise ValueError(f"{name} is not the file of the manifest")
                if rows:
                    yield _read_batch(rows)

    return read


class _Tee:
    def __init__(self, f, check):
        self.f, self.check = f, check

    def read(self, size):
        data = self.f.read(size)
        self.check.update(data)
        return data


def _read_batch(rows):
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=[x.split()[0] for x in READ.split(", ")])


def read_archives(where: str, manifest: DataFrame, payloads: bool = False) -> DataFrame:
    """Records of all files of the manifest; files missing from it do not count, damaged ones are errors."""
    files = manifest.select("file", "sha256").repartition(max(1, manifest.count()))  # a task a file, not coalesced
    return files.mapInArrow(_reading(where, payloads), READ)
