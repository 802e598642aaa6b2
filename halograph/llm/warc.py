"""WARC archives written by Spark's text sink and read back by byte ranges along verified record boundaries.

Writing is declarative: one string a record, ended by the sink's line separator, so the sink's commit protocol covers
lost executors. Reading splits plain archives at any byte: the text source cuts them at blank lines, which end every
header and every record, so a header is one piece. Each task lists the places of its block at which a header stands and
the offset at which the next record would begin; headers inside payloads look the same. Only the chain from the start of
the file is real: pointer jumping over the exits of the blocks finds where it enters each block. Records of a block are
put together on the way, from its first header on; blocks that the chain enters elsewhere are read once more, and records
that cross blocks are joined from their parts.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from halograph.llm.common import Scratch

CRLF = "\r\n"
BLANK = b"\r\n\r\n"
VERSION = b"WARC/1.1\r\n"
_START = re.compile(rb"(?:\r\n)?(?=WARC/1\.[01]\r\n)")
#: Bytes of records that a task holds before it sends them on.
HELD_BYTES = 8 << 20
_RECORD = "record_id string, record_type string, refers_to string, target_uri string, payload_bytes long, payload_digest string, payload binary, sound boolean"


def _clean(value: Column) -> Column:
    """Header values hold no line ends."""
    return F.regexp_replace(value, r"[\x00-\x1F\x7F]", " ")


def _header(name: str, value: Column) -> Column:
    return F.coalesce(F.concat(F.lit(name + ": "), value, F.lit(CRLF)), F.lit(""))


def plan_records(pages: DataFrame, least_bytes: int, scratch: Scratch) -> DataFrame:
    """page_id, url, html, n, digest and, for records that revisit another, the identifier of that record.

    Only identifiers and digests meet to find equal payloads; the payloads move once, by identifier.
    """
    body = F.coalesce("html", F.lit(""))
    sized = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), body.alias("html"))
    sized = sized.withColumns({"n": F.octet_length("html").cast("long"), "digest": F.sha2("html", 256)})
    keys = sized.filter(F.col("n") >= least_bytes).select("page_id", "digest")
    first = keys.groupBy("digest").agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("rows")).filter("rows > 1").select("digest", "first_id")
    again = keys.join(first, "digest").filter("page_id IS NULL OR page_id <> first_id").filter("first_id IS NOT NULL").distinct()
    # Written, so that its size is known: where it is small, payloads need not move at all.
    again = scratch.keep(again.select(F.col("page_id").alias("_id"), F.col("digest").alias("_digest"), F.col("first_id").alias("refers_to")), "revisits")
    return sized.join(again, sized.page_id.eqNullSafe(again._id) & (sized.digest == again._digest), "left").drop("_id", "_digest")


def record_text(date: str = "2024-01-01T00:00:00Z") -> Column:
    """The whole record, without the two line ends that close it."""
    revisit = F.col("refers_to").isNotNull()
    identity = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("none")), F.lit(">"))
    http = F.concat(F.lit(f"HTTP/1.1 200 OK{CRLF}Content-Type: text/html; charset=utf-8{CRLF}Content-Length: "), F.col("n").cast("string"), F.lit(CRLF * 2))
    block = F.when(revisit, http).otherwise(F.concat(http, F.col("html")))
    size = F.octet_length(http) + F.when(revisit, F.lit(0)).otherwise(F.col("n"))
    return F.concat(
        F.lit(VERSION.decode()),
        _header("WARC-Type", F.when(revisit, F.lit("revisit")).otherwise(F.lit("response"))),
        _header("WARC-Record-ID", identity(F.col("page_id"))),
        _header("WARC-Date", F.lit(date)),
        _header("WARC-Target-URI", _clean(F.col("url"))),
        _header("WARC-Payload-Digest", F.concat(F.lit("sha256:"), F.col("digest"))),
        _header("WARC-Refers-To", F.when(revisit, identity(F.col("refers_to")))),
        _header("WARC-Profile", F.when(revisit, F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"))),
        _header("Content-Type", F.lit("application/http; msgtype=response")),
        _header("Content-Length", size.cast("string")),
        F.lit(CRLF),
        block,
    )


def write_warc(pages: DataFrame, path: str, *, least_bytes: int = 100, files: int | None = None, codec: str = "none", scratch: Scratch | None = None) -> str:
    """Writes a record for each row of pages (page_id, url, html) to archive files under ``path``.

    Of equal payloads of at least ``least_bytes``, the smallest page_id is a response and the others revisit it. A null
    html is empty, a null url leaves its header out, a null page_id is never the one referred to while another is there.
    Rows that repeat the smallest page_id are responses too. An empty table writes no record. Other columns are ignored.
    Headers and payloads may be of any length up to that of a string. ``files`` asks for so many files, else there are as
    many as the plan has partitions. Archives are plain, so that they can be read in parts, unless a codec is named.
    """
    planned = plan_records(pages, least_bytes, scratch or Scratch(pages.sparkSession))
    if files:
        planned = planned.repartition(files, F.xxhash64("page_id", "url"))
    planned.select(record_text().alias("value")).write.option("lineSep", CRLF * 2).text(path, compression=codec)
    return path


def _headers(raw: bytes) -> dict[str, str]:
    got = {}
    for line in raw.split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if colon:
            got[name.strip().lower().decode("latin-1")] = value.strip().decode("utf-8", "replace")
    return got


def _number(digits: str) -> int | None:
    """The number that ASCII digits write, if it can be a length of bytes."""
    return int(digits) if digits.isascii() and digits.isdigit() and len(digits) <= 18 else None


def _length(header: bytes) -> int | None:
    """The content length that a header states last, if it is one."""
    found = None
    for line in header.split(b"\r\n")[1:]:
        name, colon, value = line.partition(b":")
        if colon and name.strip().lower() == b"content-length":
            found = _number(value.strip().decode("latin-1"))
    return found


def _parse(header: bytes, block: bytes, complete: bool, payloads: bool) -> dict:
    head = _headers(header)
    http = block.find(BLANK)
    is_http = head.get("content-type", "").startswith("application/http") and http >= 0
    kind = head.get("warc-type", "")
    digest = head.get("warc-payload-digest", "").rpartition(":")[2] or None
    if kind == "revisit":
        payload, sound = None, complete
        n = _number(_headers(block[:http]).get("content-length", "0") if http >= 0 else "0") or 0
    else:
        payload = block[http + 4 :] if is_http else block
        own = hashlib.sha256(payload).hexdigest()
        n, sound, digest = len(payload), digest in (None, own) and complete, own
    return dict(zip([x.split()[0] for x in _RECORD.split(", ")], (head.get("warc-record-id"), kind, head.get("warc-refers-to"), head.get("warc-target-uri"), n, digest, payload if payloads else None, sound)))


_KINDS = {"path": pa.string(), "block": pa.int64(), "kind": pa.string(), "at": pa.int64(), "to": pa.int64(), "header": pa.binary(), "bytes": pa.binary()}
_RECORD_TYPE = pa.struct([(x.split()[0], {"string": pa.string(), "long": pa.int64(), "binary": pa.binary(), "boolean": pa.bool_()}[x.split()[1]]) for x in _RECORD.split(", ")])
_FOUND = "path string, block long, kind string, at long, to long, header binary, bytes binary, record struct<" + _RECORD.replace(" ", ":").replace(",:", ",") + ">"


class _Block:
    """One block of a file as its pieces come in; all places are counted from its first piece.

    Rows: ``total`` (to: bytes of the block), ``entry`` (at: the first record taken), ``step`` (a header at ``at``; to: where its
    chain leaves the block or ends), ``record``, ``open`` (a record that goes on beyond the block: to: its end, header and the bytes
    so far) and ``lead`` (the bytes before the entry).
    """

    def __init__(self, path: str, block: int, entry: int | None, payloads: bool):
        self.path, self.block, self.payloads = path, block, payloads
        self.entry = entry if entry is not None else 0 if block == 0 else None
        self.next, self.pos, self.header = self.entry, 0, None
        self.steps: dict[int, int] = {}
        self.lead: list[bytes] = []
        self.rows: list[tuple] = []
        self.held = 0

    def put(self, kind: str, at=None, to=None, header=None, data=None, record=None) -> None:
        self.held += 200 + len(header or b"") + len(data or b"") + len((record or {}).get("payload") or b"")
        self.rows.append((self.path, self.block, kind, at, to, header, data, record))

    def feed(self, value: bytes) -> None:
        rel, n = self.pos, len(value)
        m = _START.match(value)
        length = _length(value[m.end() :]) if m else None
        at = rel + m.end() if length is not None else None
        if at is not None:
            self.steps[at] = rel + n + 4 + length + 4
            if self.entry is None:
                self.entry = self.next = at
        if self.entry is None or rel < self.entry:
            whole = value + BLANK
            self.lead.append(whole if self.entry is None else whole[: self.entry - rel])
        self.pos = rel + n + 4
        if self.header is not None:
            if rel < self.end:
                self.content.append((value + BLANK)[: self.end - rel] if self.pos > self.end else value + BLANK)
            if self.end + 4 <= (self.pos if at is None else at):
                self.close()
        if self.header is None and at is not None and at == self.next:
            self.at, self.header, self.content = at, value[m.end() :], []
            self.end = self.pos + length

    def close(self) -> None:
        self.put("record", self.at, self.end + 4, record=_parse(self.header, b"".join(self.content), True, self.payloads))
        self.next, self.header = self.end + 4, None

    def finish(self) -> None:
        if self.header is not None and self.end + 4 <= self.pos:
            self.close()
        if self.header is not None:
            self.put("open", self.at, self.end + 4, self.header, b"".join(self.content))
        if self.lead and self.block:
            self.put("lead", data=b"".join(self.lead))
        self.put("total", to=self.pos)
        if self.entry is not None:
            self.put("entry", self.entry)
        leaves: dict[int, int] = {}
        for at in sorted(self.steps, reverse=True):
            leaves[at] = leaves.get(self.steps[at], self.steps[at])
            self.put("step", at, leaves[at])

    def taken(self) -> pa.RecordBatch:
        cols = [pa.array([r[k] for r in self.rows], t) for k, t in enumerate(_KINDS.values())]
        out = pa.RecordBatch.from_arrays([*cols, pa.array([r[7] for r in self.rows], _RECORD_TYPE)], names=[*_KINDS, "record"])
        self.rows, self.held = [], 0
        return out


def _scan(payloads: bool):
    """Rows of all blocks from pieces (path, block, value and, on the second reading, entry) in the order of the file."""

    def run(batches):
        now = None
        for batch in batches:
            path, block, value = (batch.column(k) for k in range(3))
            entry = batch.column(3) if batch.num_columns > 3 else None
            for i, key in enumerate(zip(path.to_pylist(), block.to_pylist())):
                if now is None or key != (now.path, now.block):
                    if now is not None:
                        now.finish()
                        yield now.taken()
                    now = _Block(*key, entry[i].as_py() if entry is not None else None, payloads)
                now.feed(value[i].as_py())
                if now.held > HELD_BYTES:
                    yield now.taken()
        if now is not None:
            now.finish()
            yield now.taken()

    return run


def _numbered(batches):
    """path, block, n, value: pieces of a block, numbered."""
    now, n = None, 0
    for batch in batches:
        keys = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
        numbers = []
        for key in keys:
            n = n + 1 if key == now else 0
            now = key
            numbers.append(n)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(numbers, pa.int64()), batch.column(2)], names=["path", "block", "n", "value"])


def _whole(payloads: bool):
    """A record that crosses blocks, from its open part and the leads of the blocks that follow."""

    def run(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda r: r["base"])
        first = rows[0]
        length = _length(first["header"])
        body = b"".join([first["bytes"], *(r["lead"] or b"" for r in rows)])
        # what the last piece of a file lacks of its closing line ends was counted with the block
        record = _parse(first["header"], body[:length], len(body) >= length and bool(first["closed"]), payloads)
        return pa.table([pa.array([first["path"]]), pa.array([first["offset"]], pa.int64()), pa.array([record], _RECORD_TYPE)], names=["path", "offset", "record"])

    return run


def reachable_entries(steps: DataFrame, scratch: Scratch) -> DataFrame:
    """path, entry: where the chain from offset 0 enters blocks, by pointer jumping over steps (path, entry, leaves)."""
    longest = steps.groupBy("path").count().agg(F.max("count")).first()[0] or 0
    reached = steps.filter("entry = 0").select("path", "entry")
    jump = steps.select("path", "entry", "leaves")
    known = 1
    while known < longest:  # after each round the chain is known twice as many blocks far
        further = reached.join(jump, ["path", "entry"]).select("path", F.col("leaves").alias("entry"))
        reached = scratch.keep(reached.union(further).distinct(), "reached")
        onward = jump.select("path", F.col("entry").alias("leaves"), F.col("leaves").alias("next"))
        known *= 2
        if known < longest:
            jump = scratch.keep(jump.join(onward, ["path", "leaves"]).select("path", "entry", F.col("next").alias("leaves")), "jump")
    return reached.join(steps.select("path", "entry"), ["path", "entry"], "left_semi")


def read_warc(spark: SparkSession, path: str, *, scratch: Scratch | None = None, payloads: bool = True) -> DataFrame:
    """path, offset and the fields of all records reachable from the start of each archive file under ``path``.

    Plain files are read in parts of spark.sql.files.maxPartitionBytes by as many tasks; a file named .gz, of one or many
    members, streams through one task. Text inside a payload that looks like a record is never one. ``sound`` is false where
    a payload differs from its recorded digest or is cut short. Where a chain breaks before the end of its file (no
    record stands where the last one says), a row without record_id tells the place, with sound = false. An empty folder
    gives no rows. A record, also one that crosses parts, is held by one task and may have up to 2 GB.
    """
    scratch = scratch or Scratch(spark)
    text = spark.read.option("lineSep", CRLF * 2).text(path)
    pieces = text.select(F.col("_metadata.file_path").alias("path"), F.col("_metadata.file_block_start").alias("block"), F.col("value").cast("binary").alias("value"))
    found = scratch.keep(pieces.mapInArrow(_scan(payloads), _FOUND), "found")
    before = F.sum("to").over(Window.partitionBy("path").orderBy("block").rowsBetween(Window.unboundedPreceding, -1))
    blocks = scratch.keep(found.filter("kind = 'total'").select("path", "block", F.coalesce(before, F.lit(0)).alias("base"), F.col("to").alias("total")), "blocks")
    at = lambda df: df.join(blocks, ["path", "block"])
    headers = at(found.filter("kind = 'step'").select("path", "block", "at", "to")).select("path", "block", (F.col("base") + F.col("at")).alias("entry"), (F.col("base") + F.col("to")).alias("leaves"), "base")
    starts = blocks.groupBy("path").agg(F.sum("total").alias("size"))
    targets = headers.select("path", F.col("leaves").alias("entry")).union(starts.select("path", F.lit(0).cast("long"))).distinct()
    steps = scratch.keep(headers.join(targets, ["path", "entry"]), "steps")
    reached = scratch.keep(reachable_entries(steps, scratch), "entries")
    real = steps.join(reached, ["path", "entry"], "left_semi")
    # Blocks that the chain enters elsewhere than at their first header, or not at all.
    wrong = (
        blocks.join(found.filter("kind = 'entry'").select("path", "block", F.col("at").alias("taken")), ["path", "block"], "left")
        .join(real.select("path", "block", (F.col("entry") - F.col("base")).alias("met")), ["path", "block"], "left")
        .filter("NOT taken <=> met AND taken IS NOT NULL")
        .select("path", "block", F.coalesce("met", F.lit(1 << 62)).alias("entry"))
    )
    wrong = scratch.keep(wrong, "wrong")
    if not wrong.isEmpty():
        again = pieces.mapInArrow(_numbered, "path string, block long, n long, value binary").join(wrong, ["path", "block"])
        again = again.repartition("path", "block").sortWithinPartitions("path", "block", "n").select("path", "block", "value", "entry")
        right = found.join(wrong, ["path", "block"], "left_anti").select(found.columns)
        found = scratch.keep(right.unionByName(again.mapInArrow(_scan(payloads), _FOUND)), "found again")
    offset = (F.col("base") + F.col("at")).alias("offset")
    inside = at(found.filter("kind = 'record'").select("path", "block", "at", "record")).select("path", offset, "record")
    opened = at(found.filter("kind = 'open'").select("path", "block", "at", "to", "header", "bytes")).join(starts, "path")
    opened = opened.select("path", offset, (F.col("base") + F.col("to")).alias("until"), "header", "bytes", (F.col("base") + F.col("to") <= F.col("size")).alias("closed"))
    leads = at(found.filter("kind = 'lead'").select("path", "block", F.col("bytes").alias("lead"))).select(F.col("path").alias("_path"), "base", "lead")
    parts = opened.join(leads, (F.col("path") == F.col("_path")) & (F.col("base") > F.col("offset")) & (F.col("base") < F.col("until")), "left")
    crossing = parts.drop("_path").groupBy("path", "offset").applyInArrow(_whole(payloads), "path string, offset long, record struct<" + _RECORD.replace(" ", ":").replace(",:", ",") + ">")
    # Where the chain should go on but no header stands.
    ends = real.select("path", F.col("leaves").alias("entry")).union(starts.select("path", F.lit(0).cast("long")))
    lost = ends.join(headers.select("path", "entry"), ["path", "entry"], "left_anti").join(starts, "path").filter("entry < size")
    nothing = [F.lit(None).cast(kind).alias(name) for name, kind in (x.split() for x in _RECORD.split(", ")) if name != "sound"]
    broken = lost.select("path", F.col("entry").alias("offset"), F.struct(*nothing, F.lit(False).alias("sound")).alias("record"))
    return inside.unionByName(crossing).unionByName(broken).select("path", "offset", "record.*")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark)
    path = write_warc(spark.read.parquet(f"{sf_dir}/pages.parquet"), scratch.path("warc"), scratch=scratch)
    records = read_warc(spark, path, scratch=scratch, payloads=False)
    page = lambda c: F.regexp_extract(c, r"urn:page:(-?\d+)", 1).try_cast("long")
    return records.select(page(F.col("record_id")).alias("page_id"), "payload_bytes", "payload_digest", "record_type", page(F.col("refers_to")).alias("refers_to"))


OP8_SQL = """
WITH p AS (
  SELECT page_id, strlen(coalesce(html, '')) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_id FROM p)
SELECT page_id, payload_bytes, payload_digest,
  CASE WHEN payload_bytes >= 100 AND first_id <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN payload_bytes >= 100 AND first_id <> page_id THEN first_id END AS refers_to
FROM f
"""
