"""WARC archives by Spark's own readers and writers, with a check of the chain of record boundaries.

Writing: a record per page, the payload in full in the response record of each payload and left out in its revisits.
Reading: archives are split at every occurrence of the record magic, and what is read is written down before
anything refers to it, so that no two scans have to come to the same parts. Each part between two magics is a
candidate record, told by its byte offset in its file, and its declared length points to its successor. Tasks follow
these pointers within their split of a file; where chains leave a split, joins carry on by pointer jumping, from the
start of each file. What is not reached only looks like a record inside a payload.

Spark's text writer compresses a file as one gzip member, which readers take whole; files are kept small for that, and
``compression="none"`` gives files that are read in splits. A file of any size is followed split by split.
"""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import release, shared_dir, store, table

MAGIC = "WARC/1.1\r\n"
DATE = "2024-01-01T00:00:00Z"
#: Payloads from this size on are written once, and records in a file at most.
LEAST_BYTES, RECORDS = 0, 5_000
#: What stands for a missing url, since records of these kinds must have one; the profile of revisits.
NO_URL, PROFILE = "urn:page:none", "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
#: Digits of base 32, as Spark's conv writes them and as digests do.
CONV, BASE32 = "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"


def base32_sha1(payload: Column) -> Column:
    """The bare upper-case base-32 SHA-1: 40 hex digits in eight parts of 20 bits, each four digits."""
    h = F.sha1(payload)
    return F.translate(F.concat(*[F.lpad(F.conv(F.substring(h, 5 * i + 1, 5), 16, 32), 4, "0") for i in range(8)]), CONV, BASE32)


def write(pages: DataFrame, path: str, least_bytes: int = LEAST_BYTES, compression: str = "gzip") -> None:
    """Write ``pages(page_id, url, html)`` as WARC files under ``path``.

    A null html is an empty payload, a null page_id leaves its header out, a null url is named ``NO_URL``. Of equal
    payloads the one with the largest page_id is the response (rows with a null page_id are responses always); rows
    equal in both are responses all. Every record has an id of its own. An empty table gives no records.
    """
    url = F.regexp_replace(F.coalesce("url", F.lit(NO_URL)), r"[\r\n]", "")
    p = pages.select("page_id", url.alias("url"), F.coalesce("html", F.lit("")).alias("html"))
    p = p.withColumn("bytes", F.octet_length("html")).withColumn("digest", base32_sha1(F.col("html").cast("binary")))
    last = store(p.where((F.col("bytes") >= least_bytes) & F.col("page_id").isNotNull()).groupBy("digest").agg(F.max(F.struct("page_id", "url")).alias("last")), "last")
    p = p.join(last, "digest", "left")
    revisit = F.coalesce(F.col("page_id") < F.col("last.page_id"), F.lit(False)) & (F.col("bytes") >= least_bytes)
    block = F.when(revisit, "").otherwise(F.col("html"))
    line = lambda name, value: F.coalesce(F.concat(F.lit(f"{name}: "), value, F.lit("\r\n")), F.lit(""))
    again = lambda name, value: F.when(revisit, line(name, value)).otherwise("")
    record = F.concat(
        F.lit(MAGIC), line("WARC-Type", F.when(revisit, "revisit").otherwise("response")), line("WARC-Record-ID", F.concat(F.lit("<urn:uuid:"), F.uuid(), F.lit(">"))), line("WARC-Target-URI", F.col("url")), F.lit(f"WARC-Date: {DATE}\r\n"),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))), again("WARC-Profile", F.lit(PROFILE)), again("WARC-Refers-To-Target-URI", F.col("last.url")), again("WARC-Refers-To-Date", F.lit(DATE)),
        line("Page-ID", F.col("page_id").cast("string")), again("Refers-To-Page-ID", F.col("last.page_id").cast("string")), line("Full-Payload-Length", F.col("bytes").cast("string")),
        F.lit("Content-Type: text/html; charset=utf-8\r\n"), line("Content-Length", F.octet_length(block).cast("string")), F.lit("\r\n"), block, F.lit("\r\n"))
    # the line separator ends each record with its second line end
    p.select(record.alias("value")).write.options(lineSep="\r\n", maxRecordsPerFile=RECORDS, compression=compression).text(path)


def _order(t: pa.Table) -> tuple[pa.Table, np.ndarray, np.ndarray, np.ndarray]:
    """Candidates of one split in order; their offsets, where their successors should be, and which of them that is (n: none here)."""
    t = t.sort_by("no")
    size, head, body = (t.column(c).fill_null(-1).to_numpy() for c in ("size", "head_bytes", "body"))
    n, magic = len(size), len(MAGIC)
    offset = t.column("base")[0].as_py() + np.cumsum(size + magic) - size - 2 * magic  # what stands before a file's first magic is at -magic
    after = np.where((head >= 0) & (body >= 0) & (offset >= 0), offset + magic + head + 4 + body + 4, -1)
    at = np.searchsorted(offset, after)
    jump = np.where((after >= 0) & (at < n) & (offset[np.minimum(at, n - 1)] == after), at, n)
    return t, offset, after, jump


def _exits(t: pa.Table) -> pa.Table:
    """For each candidate of a split the place at which its chain leaves the split, if it does so where a record may begin."""
    t, offset, after, jump = _order(t)
    n, end = len(offset), t.column("base")[0].as_py() + int(sum(t.column("size").to_numpy() + len(MAGIC))) - len(MAGIC)
    step = np.append(np.where(jump < n, jump, np.arange(n)), n)
    while True:  # after round r, 2**r steps are done
        more = step[step]
        if (more == step).all():
            break
        step = more
    out = after[step[:n]]
    good = (after >= 0) & (out >= end)
    return pa.table({"file": t.column("file").filter(pa.array(good)), "part": t.column("part").filter(pa.array(good)), "offset": pa.array(offset[good]), "exit": pa.array(out[good])})


def _reached(t: pa.Table) -> pa.Table:
    """Candidates of a split with the place where the file's chain enters it -> which are records, and the record that each belongs to."""
    t, offset, after, jump = _order(t)
    n, total, enter = len(offset), t.column("total")[0].as_py(), t.column("enter")[0].as_py()
    reach = np.zeros(n + 1, bool)
    if enter is not None:
        reach[:n] = offset == enter
    step = np.append(jump, n)
    while True:  # after round r all records within 2**r of the entry are reached
        more = reach.copy()
        more[step[np.flatnonzero(reach)]] = True
        if (more == reach).all():
            break
        reach, step = more, step[step]
    leaves = np.isin(after, np.array(t.column("starts")[0].as_py() or [], np.int64))
    whole = reach[:n] & ((jump < n) | (after == total) | leaves)  # a record ends where another begins, or with the file
    at = np.flatnonzero(whole)
    owner = np.searchsorted(at, np.arange(n), side="right") - 1
    first = np.where(owner >= 0, at[np.maximum(owner, 0)] if len(at) else 0, 0)
    own = np.where(owner >= 0, offset[first], -1)
    until = np.where(owner >= 0, after[first], -1)
    none = owner < 0
    return pa.table({"file": t.column("file"), "part": t.column("part"), "no": t.column("no"), "offset": pa.array(offset), "record": pa.array(own, pa.int64(), mask=none), "until": pa.array(until, pa.int64(), mask=none)})


HEAD = r"substring_index(value, '\r\n\r\n', 1)"
BODY = rf"try_cast(regexp_extract({HEAD}, '(?i)(?:^|\n)Content-Length:[ \t]*(\\d+)', 1) as long)"


def _payload(size: str) -> Column:
    return F.expr(f"substring(cast(value as binary), cast(octet_length(head) + 5 as int), cast({size} as int))")


def chain(parts: DataFrame) -> DataFrame:
    """Candidates ``parts(file, part, no, size, head_bytes, body)`` -> ``file, part, no, record, pieces, offset`` of those in records.

    ``record`` is the offset of the record that a candidate belongs to, ``pieces`` the number of its candidates. A split
    (``part``) is one task's; between splits only the few places where chains leave them are joined.
    """
    magic = len(MAGIC)
    splits = store(parts.groupBy("file", "part").agg(F.sum(F.col("size") + magic).alias("bytes")), "splits")
    in_file = Window.partitionBy("file").orderBy("part")
    splits = splits.withColumns({"base": F.sum("bytes").over(in_file) - F.col("bytes"), "total": F.sum("bytes").over(Window.partitionBy("file")) - magic})
    splits = store(splits, "bases")
    based = parts.join(splits.select("file", "part", "base"), ["file", "part"])
    kinds = "file string, part long, offset long, exit long"
    exits = store(based.groupBy("file", "part").applyInArrow(_exits, kinds), "exits")
    # places that a chain of another split comes to, and starts of files
    aims = exits.select("file", F.col("exit").alias("offset")).distinct()
    doors = store(exits.join(aims, ["file", "offset"], "left_semi").union(exits.where("offset = 0")).distinct(), "doors")
    hops = store(doors.select("file", "offset", "exit"), "hops")
    reach = store(doors.where("offset = 0").select("file", "offset"), "reach")
    first = parts.select("file").distinct().withColumn("offset", F.lit(0).cast("long"))
    reach = store(reach.union(first).distinct(), "reach")
    before = reach.count()
    while True:  # after round r all doors within 2**r of a file's start are reached
        reach, old = store(reach.union(reach.join(hops, ["file", "offset"]).select("file", F.col("exit").alias("offset"))).distinct(), "reach"), reach
        release(old)
        if (now := reach.count()) == before:
            break
        before = now
        far = hops.select("file", F.col("offset").alias("exit"), F.col("exit").alias("far"))
        hops, old = store(hops.join(far, ["file", "exit"]).select("file", "offset", F.col("far").alias("exit")), "hops"), hops
        release(old)
    enter = doors.join(reach, ["file", "offset"], "left_semi").select("file", "part", F.col("offset").alias("enter")).union(
        splits.where("base = 0").select("file", "part", F.lit(0).cast("long").alias("enter"))).distinct()
    starts = reach.groupBy("file").agg(F.collect_set("offset").alias("starts"))  # a door a split at most
    splits = splits.join(enter, ["file", "part"], "left").join(starts, "file", "left")
    # a chain's last part may be entered without leaving it: its door is where the last exit leads
    led = reach.join(splits.select("file", "part", "base", "bytes"), "file").where(f"offset >= base - {magic} and offset < base + bytes - {magic}").select("file", "part", F.col("offset").alias("led"))
    splits = store(splits.join(led.groupBy("file", "part").agg(F.min("led").alias("led")), ["file", "part"], "left").select("file", "part", "base", "total", F.coalesce("enter", "led").alias("enter"), "starts"), "entries")
    kinds = "file string, part long, no long, offset long, record long, until long"
    held = store(parts.join(splits, ["file", "part"]).groupBy("file", "part").applyInArrow(_reached, kinds), "reached")
    # the last record of a split may go on in the next ones
    tails = held.groupBy("file", "part").agg(F.max(F.struct("record", "until")).alias("t"))
    tails = tails.select("file", "part", F.last(F.when(F.col("t.record").isNotNull(), F.col("t")), ignorenulls=True).over(in_file.rowsBetween(Window.unboundedPreceding, -1)).alias("t"))
    held = held.join(tails, ["file", "part"]).withColumns({"record": F.coalesce("record", "t.record"), "until": F.coalesce("until", "t.until")})
    held = store(held.where("record is not null and offset < until").select("file", "part", "no", "offset", "record"), "held")
    sizes = held.groupBy("file", "record").agg(F.count("*").alias("pieces"))
    return store(held.join(sizes, ["file", "record"]), "chain")


def read(spark: SparkSession, path: str, payload: bool = True) -> DataFrame:
    """Reachable records of the archives under ``path``: page_id, type, url, digest and length of the payload, and itself if asked for.

    What is asked for of each candidate is written down with its file, split and place in it, before anything refers to
    that. Files in which records have the magic in their payload are read again, and such records are put together
    from their pieces. Archives without records give no rows.
    """
    raw = spark.read.option("lineSep", MAGIC).text(path)
    placed = raw.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("part"), F.monotonically_increasing_id().alias("no"), "value")
    parts = placed.select("*", F.octet_length("value").cast("long").alias("size"), F.expr(HEAD).alias("head"), F.expr(BODY).alias("body"))
    parts = parts.withColumn("head_bytes", F.when(F.instr("value", "\r\n\r\n") > 0, F.octet_length("head").cast("long")))
    alone = F.coalesce(F.octet_length("head") + 8 + F.col("body") == F.col("size"), F.lit(False))
    keep = ["file", "part", "no", "size", "head_bytes", "body", "head"]
    record = [base32_sha1(F.col("payload")).alias("digest"), F.octet_length("payload").cast("long").alias("bytes"), *["payload"] * payload]
    even = store(parts.withColumn("payload", F.when(alone, _payload("body"))).select(*keep, (~alone & (F.col("size") > 0)).alias("odd"), *record), "candidates")
    # files in which some candidate is no record in itself are read again, with the texts of all of theirs
    files = store(even.where("odd").select("file").distinct(), "odd")
    n = files.count()
    known = F.broadcast(files) if n <= 10_000 else files
    candidates = even.withColumn("value", F.lit(None).cast("string"))
    if n:
        odd = store(parts.join(known, "file").select(*keep, "value"), "odd")
        candidates = even.join(known, "file", "left_anti").withColumn("value", F.lit(None).cast("string")).unionByName(odd, allowMissingColumns=True)
    parts = candidates
    chained = chain(parts.select("file", "part", "no", "size", "head_bytes", "body"))
    columns = ["head", "digest", "bytes", *["payload"] * payload]
    found = parts.join(chained, ["file", "part", "no"])
    kept = found.where("value is null").select(*columns)
    several = found.where("value is not null").groupBy("file", "record").agg(F.sort_array(F.collect_list(F.struct("offset", "value"))).alias("v")).select(F.array_join("v.value", MAGIC).alias("value"))
    several = several.select(F.expr(HEAD).alias("head"), F.expr(BODY).alias("body"), "value").select("head", _payload("body").alias("payload"))
    r = kept.union(several.select("head", base32_sha1(F.col("payload")).alias("digest"), F.octet_length("payload").cast("long").alias("bytes"), *["payload"] * payload))
    named = lambda name: F.regexp_extract("head", rf"(?i)(?:^|\n){name}:[ \t]*([^\r\n]*)", 1)
    number = lambda name: F.expr("try_cast(" + rf"regexp_extract(head, '(?i)(?:^|\n){name}:[ \t]*(-?\\d+)', 1) as long)")
    full = named("WARC-Type") != "revisit"
    told = F.regexp_replace(named("WARC-Payload-Digest"), "^sha1:", "")
    return r.select(
        number("Page-ID").alias("page_id"), F.nullif(F.nullif(named("WARC-Target-URI"), F.lit("")), F.lit(NO_URL)).alias("url"), named("WARC-Type").alias("record_type"), number("Refers-To-Page-ID").alias("refers_to"),
        F.when(full, F.col("bytes")).otherwise(number("Full-Payload-Length")).alias("payload_bytes"),
        F.when(full, F.col("digest")).otherwise(told).alias("payload_digest"), (~full | (told == F.col("digest"))).alias("intact"), *["payload"] * payload)


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark)}/warc-{uuid.uuid4().hex}"
    write(table(spark, sf_dir, "pages"), path)
    return read(spark, path, payload=False).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = """
WITH p AS (SELECT page_id, coalesce(html, '') AS html FROM pages),
d AS (SELECT page_id, octet_length(encode(html)) AS n, sha1(html) AS h FROM p),
v AS (SELECT page_id, n, h, list_transform(range(8), lambda i: CAST('0x' || substr(h, CAST(5 * i + 1 AS BIGINT), 5) AS BIGINT)) AS g FROM d),
b AS (SELECT page_id, n, h, array_to_string(list_transform(g, lambda x: array_to_string(list_transform([15, 10, 5, 0], lambda s: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(1 + (x >> s) % 32 AS BIGINT), 1)), '')), '') AS payload_digest FROM v),
m AS (SELECT h, max(page_id) AS last FROM d GROUP BY h)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, payload_digest, CASE WHEN page_id < last THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id < last THEN last END AS refers_to FROM b JOIN m USING (h)
"""
