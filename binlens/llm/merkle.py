"""Merkle fixity audit of archive records.

A record is a response block (request line, length, payload); its leaf is the SHA-256 of its bytes.  Leaves are
ordered by record key, the order in which records stand in the file, and ranges of ``fan`` keys hash to the next level,
up to one root; ranges go by key and not by offset, as a lost byte would move all offsets behind it.  Two replicas are
compared from the root down; only children of mismatching nodes are looked at, so intact branches cost nothing
beyond their top.  Nodes also carry the byte range that they cover.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.llm.common import settle

FAN = 64


def record_text(url: Column, body: Column) -> Column:
    """Bytes of a response record, as text: type, target, payload length in bytes, payload.  A record without a target
    has no line for it, and one without a payload is marked as truncated, so neither equals one with an empty value."""
    target = F.coalesce(F.concat(F.lit("\nWARC-Target-URI: "), url), F.lit(""))
    mark = F.when(body.isNull(), "\nWARC-Truncated: unspecified").otherwise("")
    body = F.coalesce(body, F.lit(""))
    return F.concat(F.lit("WARC/1.1\nWARC-Type: response"), target, mark, F.lit("\nContent-Length: "), F.octet_length(body).cast("string"),
        F.lit("\n\n"), body, F.lit("\n\n"))


def records(pages: DataFrame, key: str = "page_id", url: str = "url", body: str = "html") -> DataFrame:
    """(key, size, hash): one row for each key, and one for all rows without a key.  Rows that share a key are one leaf,
    made from their hashes' smallest and largest, their sum and count, so no list of them is ever held."""
    text = record_text(F.col(url).cast("string"), F.col(body).cast("string"))
    rows = pages.select(F.col(key).cast("long").alias("key"), text.alias("record"))
    rows = rows.select("key", F.octet_length("record").cast("long").alias("size"), F.sha2("record", 256).alias("hash"))
    total = F.sum(F.conv(F.substring("hash", 1, 12), 16, 10).cast("decimal(38,0)"))
    several = F.sha2(F.concat_ws("|", F.min("hash"), F.max("hash"), total.cast("string"), F.count("*").cast("string")), 256)
    return rows.groupBy("key").agg(F.sum("size").alias("size"), F.when(F.count("*") == 1, F.min("hash")).otherwise(several).alias("hash"))


def _up(level: DataFrame, fan: int) -> DataFrame:
    """Nodes over at most ``fan`` children each."""
    children = F.sort_array(F.collect_list(F.struct("key", "hash")))
    return level.groupBy(F.floor(F.col("key") / fan).cast("long").alias("key")).agg(F.sum("size").alias("size"), F.sha2(F.concat_ws("",
        F.transform(children, lambda c: c["hash"])), 256).alias("hash"))


def tree(leaves: DataFrame, fan: int = FAN, height: int | None = None) -> list[DataFrame]:
    """Levels (key, size, hash), leaves first, a single root last.  Keys must not be negative.

    ``height`` fixes the number of levels above the leaves (for two replicas: the taller one's)."""
    levels = [settle(leaves, "level")]
    if height is None:
        height = height_of(levels[0], fan)
    for _ in range(height):
        levels.append(settle(_up(levels[-1], fan), "level"))
    return levels


def height_of(leaves: DataFrame, fan: int = FAN) -> int:
    top, h = leaves.agg(F.max("key")).first()[0] or 0, 1
    while top >= fan:
        top, h = top // fan, h + 1
    return h


def _offsets(levels: list[DataFrame], fan: int, wanted: list[DataFrame]) -> DataFrame:
    """(key, start, size) of the leaves below ``wanted`` nodes: sums over siblings only, from the root down."""
    at = levels[-1].select("key", F.lit(0).cast("long").alias("start"))
    for level, keep in zip(reversed(levels[:-1]), wanted):
        siblings = level.withColumn("parent", F.floor(F.col("key") / fan).cast("long")).join(at.select(F.col("key").alias("parent"),
            F.col("start").alias("origin")), "parent")
        before = F.sum("size").over(Window.partitionBy("parent").orderBy("key")) - F.col("size")
        at = siblings.withColumn("start", F.col("origin") + before).join(keep.select("key"), "key", "left_semi").select("key", "start", "size")
    return at


def audit(ours: DataFrame, theirs: DataFrame, fan: int = FAN) -> DataFrame:
    """(key, start, size, our_hash, their_hash, nodes_compared): records that differ, are missing or are added.

    start and size: the byte range in our replica, records in key order and those without a key last; null where only
    the other one has the record.  Keys may be negative: they count from the smallest of both replicas.  The leaf of the
    rows without a key has a null key.  Equal roots end the audit at once with no rows; two empty replicas are equal.
    """
    a, b = settle(ours, "replica"), settle(theirs, "replica")
    ends = a.select("key").union(b.select("key")).agg(F.min("key").alias("lo"), F.max("key").alias("hi")).first()
    lo, hi = ends.lo or 0, ends.hi or 0
    place = F.coalesce(F.col("key") - lo, F.lit(hi - lo + 1))
    a, b = (t.withColumn("key", place) for t in (a, b))
    height = max(height_of(a, fan), height_of(b, fan))
    ta, tb = tree(a, fan, height), tree(b, fan, height)
    compared = 0
    suspects: DataFrame | None = None
    path = []
    for la, lb in zip(reversed(ta), reversed(tb)):
        x, y = la, lb
        if suspects is not None:
            parent = F.floor(F.col("key") / fan).cast("long")
            up = suspects.select(F.col("key").alias("parent"))
            x, y = (t.withColumn("parent", parent).join(up, "parent", "left_semi").drop("parent") for t in (x, y))
        both = x.select("key", F.col("hash").alias("our_hash")).join(y.select("key", F.col("hash").alias("their_hash")), "key", "full_outer")
        both = settle(both, "compared")
        compared += both.count()
        suspects = both.where("not (our_hash <=> their_hash)")
        path.append(suspects)
        if suspects.isEmpty():
            break
    out = suspects
    if len(path) == height + 1:
        out = suspects.join(_offsets(ta, fan, path[1:]), "key", "left")
    else:
        out = suspects.withColumns({"start": F.lit(None).cast("long"), "size": F.lit(None).cast("long")})
    key = F.when(F.col("key") <= hi - lo, F.col("key") + lo).alias("key")
    return out.select(key, "start", "size", "our_hash", "their_hash", F.lit(compared).cast("long").alias("nodes_compared"))


def rotten(pages: DataFrame, body: str = "html") -> DataFrame:
    """A replica with bit rot, for drills: the first byte is lost in each payload whose MD5 begins with 0a."""
    return pages.withColumn(body, F.when(F.md5(body).startswith("0a"), F.expr(f"substring({body}, 2)")).otherwise(F.col(body)))
