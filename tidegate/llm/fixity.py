"""Merkle fixity audit of WARC replicas.

write_files() lays records out in WARC files, one after the other, and writes their bytes: a row holds the bytes of up to FAN
consecutive records, as files are read by ranges. A record's leaf is the SHA-256 of its bytes with its offset range; manifest() takes it while
records are written, read_manifest() by reading each record's range of stored bytes again. FAN ordered siblings hash to one
parent, up to a root a file. Two replicas are compared by their roots; only below roots that differ are the next level's hashes
joined, and so on down to the records. Trees are written to the shared folder once, and every level is a grouped
aggregation keyed by (file, node), so a large file spreads over its nodes.

Defined results: null fields are written as empty; a file holds a range of `file_records` page_ids, and rows without one lie in files
below 0, by a hash of their content, as many as their number asks for; repeated rows are records of their own; records
missing from a replica, or more than it should have, count as damaged where they lie; a file that only one replica has is
damaged as a whole; bytes that end too soon read as far as they go; empty tables give no rows; extra columns are left
out, whatever their names. Rows of one page_id, however many, are one file's, in the order of one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from tidegate.llm.common import stored

FAN = 16
FILE_RECORDS = 1024
DATE = "2024-01-01T00:00:00Z"


def record(page_id: Column, url: Column, html: Column, date: str = DATE) -> Column:
    """A WARC resource record as text; its Content-Length counts UTF-8 bytes."""
    body = F.coalesce(html, F.lit(""))
    return F.concat(
        F.lit("WARC/1.0\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:page:"), F.coalesce(page_id.cast("string"), F.lit("")),
        F.lit(f">\r\nWARC-Date: {date}\r\nWARC-Target-URI: "), F.coalesce(url, F.lit("")), F.lit("\r\nContent-Type: text/html\r\nContent-Length: "),
        F.octet_length(body).cast("string"), F.lit("\r\n\r\n"), body, F.lit("\r\n\r\n"),
    )


def _placed(pages: DataFrame, file_records: int, *keep: Column) -> DataFrame:
    """page_id, file_no, record_no, start, length, digest and `keep` of each record."""
    rec = record(F.col("page_id"), F.col("url"), F.col("html"))
    loose = 1 + pages.where(F.col("page_id").isNull()).count() // file_records
    away = -1 - F.pmod(F.xxhash64("url", "html"), F.lit(loose))
    file_no = F.coalesce(F.floor(F.col("page_id") / file_records).cast("long"), away.cast("long"))
    rows = pages.select("page_id", file_no.alias("file_no"), F.octet_length(rec).cast("long").alias("length"), F.sha2(rec, 256).alias("digest"), F.coalesce("url", F.lit("")).alias("url"), *keep)
    order = Window.partitionBy("file_no").orderBy("page_id", "url", "digest")
    return rows.withColumn("record_no", F.row_number().over(order).cast("long") - 1).withColumn("start", F.sum("length").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("length"))


def leaf_of(digest: Column) -> Column:
    return F.sha2(F.concat_ws(":", F.col("start").cast("string"), F.col("length").cast("string"), digest), 256)


def manifest(pages: DataFrame, file_records: int = FILE_RECORDS) -> DataFrame:
    """page_id, file_no, record_no, start, length and leaf of each record, as it is written."""
    return _placed(pages, file_records).select("page_id", "file_no", "record_no", "start", "length", leaf_of(F.col("digest")).alias("leaf"))


def write_files(pages: DataFrame, file_records: int = FILE_RECORDS) -> DataFrame:
    """The pages' WARC files, written to the shared folder: file_no, part_no, the part's start and bytes, and its records
    (page_id, record_no, start, length) in order."""
    placed = _placed(pages, file_records, record(F.col("page_id"), F.col("url"), F.col("html")).cast("binary").alias("bytes"))
    said = F.struct("record_no", "page_id", "start", "length", "bytes")
    parts = placed.groupBy("file_no", F.expr(f"record_no div {FAN}").alias("part_no")).agg(F.sort_array(F.collect_list(said)).alias("all"))  # FAN records at most
    index = F.transform("all", lambda r: F.struct(r["page_id"].alias("page_id"), r["record_no"].alias("record_no"), r["start"].alias("start"), r["length"].alias("length")))
    whole = F.aggregate("all", F.lit(b""), lambda x, r: F.concat(x, r["bytes"]))
    return stored(parts.select("file_no", "part_no", F.col("all")[0]["start"].alias("start"), whole.alias("bytes"), index.alias("records")), "warc")


def read_manifest(files: DataFrame) -> DataFrame:
    """manifest() of stored files: every record's offset range is read from the bytes again and hashed."""
    rows = files.select("file_no", F.col("start").alias("part_start"), "bytes", F.explode("records").alias("r")).select("file_no", "part_start", "bytes", "r.*")
    read = F.substring("bytes", (F.col("start") - F.col("part_start") + 1).cast("int"), F.col("length").cast("int"))
    return rows.select("page_id", "file_no", "record_no", "start", "length", leaf_of(F.sha2(read, 256)).alias("leaf"))


def tree(leaves: DataFrame) -> DataFrame:
    """(file_no, level, node, hash) of all levels; level 0 has a node a record. leaves should be stored: levels read them."""
    top = leaves.agg(F.max("record_no")).first()[0]
    level = leaves.select("file_no", F.lit(0).alias("level"), F.col("record_no").alias("node"), F.col("leaf").alias("hash"))
    out, width, n = level, 1 if top is None else top + 1, 0
    while width > 1:
        n, width = n + 1, -(-width // FAN)
        ordered = F.transform(F.sort_array(F.collect_list(F.struct("node", "hash"))), lambda x: x["hash"])
        up = level.groupBy("file_no", F.expr(f"node div {FAN}").alias("parent")).agg(F.sha2(F.array_join(ordered, ""), 256).alias("hash"))
        level = stored(up.select("file_no", F.lit(n).alias("level"), F.col("parent").alias("node"), "hash"), "merkle")
        out = out.unionByName(level)
    return out


def mismatches(a: DataFrame, b: DataFrame) -> DataFrame:
    """(file_no, record_no) of the records whose leaves differ, or that one tree lacks."""
    levels = max(x if x is not None else -1 for x in (t.agg(F.max("level")).first()[0] for t in (a, b)))
    # trees of different height meet at the higher one's root: a lower tree has no node there, which differs
    bad = None
    for level in range(levels, -1, -1):
        x, y = (t.where(F.col("level") == level).select("file_no", "node", F.col("hash").alias(name)) for t, name in ((a, "x"), (b, "y")))
        if bad is not None:
            x, y = (t.join(bad, (t["file_no"] == bad["bad_file"]) & (F.expr(f"node div {FAN}") == bad["bad_node"]), "left_semi") for t in (x, y))
        differ = x.join(y, ["file_no", "node"], "full").where(~F.col("x").eqNullSafe(F.col("y")))
        bad = stored(differ.select(F.col("file_no").alias("bad_file"), F.col("node").alias("bad_node")), "mismatch")
    if bad is None:
        return a.select("file_no", F.col("node").alias("record_no")).limit(0)
    return bad.select(F.col("bad_file").alias("file_no"), F.col("bad_node").alias("record_no"))


def audit(mine: DataFrame, replica: DataFrame) -> DataFrame:
    """The manifest's rows with `damaged`, and the rows that only the replica has, as damaged; replica: another manifest. Both
    are written once, so records are hashed once."""
    mine, replica = stored(mine, "manifest"), stored(replica, "manifest")
    bad, place = mismatches(tree(mine), tree(replica)), ["file_no", "record_no"]
    own = mine.join(bad.withColumn("damaged", F.lit(True)), place, "left").withColumn("damaged", F.coalesce("damaged", F.lit(False)))
    extra = replica.join(bad, place).join(mine.select(place), place, "left_anti").withColumn("damaged", F.lit(True))
    return own.unionByName(extra)
