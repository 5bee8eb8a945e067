"""Canonical exact digests of documents, with DataFrame and SQL functions only.

The canonical form of a text: compatibility composition, full case folding, composition again, runs of white space as
one space, none at the ends. Its digest is 128 bits wide, from two seeded xxhash lanes over the UTF-8 bytes. Texts of
equal digest are compared byte by byte: the smallest and the largest canonical text of a bucket are equal if all are.
A bucket that fails (none is expected) has its fingerprints extended by a SHA-256 of the canonical text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.llm.shared import id_and_text, stored

WHITE = r"[\x09-\x0D\x20\x85\p{Z}]+"


def _icu(kind: str, method: str, text: Column, option: bool) -> Column:
    """A static method of the Unicode library that Spark brings along, by Spark's SQL function ``reflect``."""
    return F.reflect(F.lit(f"com.ibm.icu.{kind}"), F.lit(method), text, F.lit(option))


def canonical(text: Column) -> Column:
    """The canonical form; ASCII texts need lower case only."""
    composed = _icu("text.Normalizer", "compose", text, True)
    wide = _icu("text.Normalizer", "compose", _icu("lang.UCharacter", "foldCase", composed, True), True)
    folded = F.when(F.octet_length(text) == F.length(text), F.lower(text)).otherwise(wide)
    return F.trim(F.regexp_replace(folded, WHITE, " "))


def lanes(canon: Column) -> list[Column]:
    return [F.xxhash64(canon), F.xxhash64(F.lit("second lane"), canon)]


def digest(high: Column, low: Column) -> Column:
    """32 lower-case hexadecimal digits."""
    return F.lower(F.concat(*[F.lpad(F.hex(x), 16, "0") for x in (high, low)]))


def digests(docs: DataFrame) -> DataFrame:
    """``doc_id, n_chars, high, low`` of every document."""
    canon = id_and_text(docs).select("doc_id", F.length("text").cast("long").alias("n_chars"), canonical(F.col("text")).alias("canon"))
    return canon.select("doc_id", "n_chars", *[x.alias(n) for x, n in zip(lanes(F.col("canon")), ("high", "low"), strict=True)])


def neighbours(ids: DataFrame) -> DataFrame:
    """``doc_id, next_id, before_id, before_chars`` of distinct doc_ids with their ``n_chars``, in a ring by ascending doc_id (null first).

    Ranges of ids are windows of their own; what lies across their borders comes from one row for each range.
    """
    spark = ids.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranges = stored(ids.repartitionByRange(n, "doc_id").select("doc_id", "n_chars", F.spark_partition_id().alias("part")), "ranges")
    own = W.partitionBy("part").orderBy("doc_id")
    inner = ranges.select(
        "*",
        F.row_number().over(own).alias("at"),
        F.lead("doc_id").over(own).alias("next_id"),
        F.lag("doc_id").over(own).alias("before_id"),
        F.lag("n_chars").over(own).alias("before_chars"),
    )
    edges = ranges.groupBy("part").agg(F.min(F.struct("doc_id", "n_chars")).alias("first"), F.max(F.struct("doc_id", "n_chars")).alias("last"), F.count("*").alias("size"))
    line = W.orderBy("part")  # as many rows as shuffle partitions
    whole = line.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    edges = edges.select(
        F.col("part").alias("of"),
        "size",
        F.coalesce(F.lead("first").over(line), F.first("first").over(whole)).alias("after"),
        F.coalesce(F.lag("last").over(line), F.last("last").over(whole)).alias("before"),
    )
    joined = inner.join(F.broadcast(edges), F.col("part") == F.col("of"))
    is_first, is_last = F.col("at") == 1, F.col("at") == F.col("size")
    return joined.select(
        "doc_id",
        F.when(is_last, F.col("after.doc_id")).otherwise(F.col("next_id")).alias("next_id"),
        F.when(is_first, F.col("before.doc_id")).otherwise(F.col("before_id")).alias("before_id"),
        F.when(is_first, F.col("before.n_chars")).otherwise(F.col("before_chars")).alias("before_chars"),
    )


def collided(canon: DataFrame) -> DataFrame:
    """``high, low`` of buckets whose canonical texts (``canon``) aren't equal byte for byte.

    Copies collapse within each task before anything is sent, so a bucket of any size costs one row a task.
    """
    bounds = canon.groupBy("high", "low").agg(F.min("canon").alias("least"), F.max("canon").alias("most"))
    return bounds.where("least <> most").select("high", "low")


def _copied(found: DataFrame) -> DataFrame:
    """``doc_id, copied`` of distinct doc_ids: whether another row has the digest of one of its rows."""
    twice = found.groupBy("high", "low").agg((F.count("*") > 1).alias("copied"))
    return found.select("doc_id", "high", "low").join(twice, ["high", "low"]).groupBy("doc_id").agg(F.max("copied").alias("copied"))


def _by_id(rows: DataFrame, more: DataFrame, how: str) -> DataFrame:
    more = more.withColumnRenamed("doc_id", "__of")
    return rows.join(more, rows["doc_id"].eqNullSafe(more["__of"]), how).drop("__of")


def exact_groups(docs: DataFrame) -> DataFrame:
    """``doc_id, fingerprint, group_id, group_size`` of every document: the smallest doc_id with its fingerprint, and how many have it."""
    found = stored(digests(docs), "digests")
    repeated = found.groupBy("high", "low").agg(F.min("doc_id").alias("group_id"), F.count("*").alias("group_size"))
    text = id_and_text(docs)
    canon = text.select("doc_id", canonical(F.col("text")).alias("canon"))
    canon = canon.select("doc_id", "canon", *[x.alias(n) for x, n in zip(lanes(F.col("canon")), ("high", "low"), strict=True)])
    bad = stored(collided(_by_id(canon, _copied(found).where("copied"), "left_semi")), "collided")
    exact = canon.join(bad, ["high", "low"], "left_semi").select("doc_id", "high", "low", F.sha2("canon", 256).alias("more")).distinct()
    groups = found.join(repeated, ["high", "low"])
    if bad.isEmpty():
        return groups.select("doc_id", digest(F.col("high"), F.col("low")).alias("fingerprint"), "group_id", "group_size")
    marked = groups.drop("group_id", "group_size").join(exact, ["doc_id", "high", "low"], "left").select("doc_id", F.concat(digest(F.col("high"), F.col("low")), F.coalesce("more", F.lit(""))).alias("fingerprint"))
    sizes = marked.groupBy("fingerprint").agg(F.min("doc_id").alias("group_id"), F.count("*").alias("group_size"))
    return marked.join(sizes, "fingerprint").select("doc_id", "fingerprint", "group_id", "group_size")


def edited(docs: DataFrame) -> DataFrame:
    """Fingerprints of every document and of its edited text: the last quarter gives way to the beginning of the next document's text.

    Rows of equal doc_id all edit with the smallest text of the next doc_id. A null text is empty; a null doc_id stands
    first. A fingerprint's likeness to another is 1 if they are equal, else 0.
    """
    known = stored(digests(docs), "digests")
    ring = neighbours(known.groupBy("doc_id").agg(F.max("n_chars").alias("n_chars")))
    ring = stored(_by_id(ring, _copied(known), "inner"), "ring")
    rows = _by_id(id_and_text(docs), ring, "inner").select("doc_id", "text", "before_id", "before_chars", "copied")
    rows = rows.withColumn("canon", canonical(F.col("text")))
    rows = rows.select("*", *[x.alias(n) for x, n in zip(lanes(F.col("canon")), ("high", "low"), strict=True)])
    bad = collided(rows.where("copied").select("high", "low", "canon")).withColumn("bad", F.lit(True))
    head = F.substr("text", F.lit(1), F.floor(F.col("before_chars") / 4).cast("int"))
    heads = rows.select(F.col("before_id").alias("for_id"), F.struct(head.alias("head"), digest(F.col("high"), F.col("low")).alias("fingerprint")).alias("next"))
    heads = heads.groupBy("for_id").agg(F.min("next").alias("next"))
    n = F.length("text")
    quarter = F.floor(n / 4).cast("int")
    both = rows.join(heads, F.col("doc_id").eqNullSafe(F.col("for_id")))
    both = both.withColumn("edited", F.concat(F.substr("text", F.lit(1), n - quarter), F.substr("next.head", F.lit(1), quarter)))
    both = both.withColumn("edited_canon", canonical(F.col("edited")))
    # digests only from here on
    both = both.select(
        "doc_id",
        "high",
        "low",
        n.cast("long").alias("n_chars"),
        F.sha2("edited", 256).alias("edited_sha256"),
        F.when(F.col("copied"), F.sha2("canon", 256)).alias("more"),
        digest(*lanes(F.col("edited_canon"))).alias("other"),
        (F.col("canon") == F.col("edited_canon")).alias("same"),
        F.col("next.fingerprint").alias("next"),
    )
    both = both.join(bad, ["high", "low"], "left")
    own, more = digest(F.col("high"), F.col("low")), F.when(F.coalesce("bad", F.lit(False)), F.col("more")).otherwise(F.lit(""))
    return both.select(
        "doc_id",
        "n_chars",
        "edited_sha256",
        F.concat(own, more).alias("fingerprint"),
        F.concat("other", F.when(F.col("same"), more).otherwise(F.lit(""))).alias("edited_fingerprint"),
        F.col("same").cast("double").alias("near_edited"),
        (own == F.col("next")).cast("double").alias("near_next"),
    )
