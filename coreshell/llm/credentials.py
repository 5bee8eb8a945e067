"""Secrets in texts: patterns of single parts, and credentials whose parts lie near each other. DataFrame and SQL functions only.

Strong parts stand alone: assigned secrets, access identifiers, long hexadecimal runs. Weak parts (account names, random
tokens, endpoints) mean nothing by themselves; one is reported only if the parts that complete it lie within its scope,
``scope`` code points to either side. That is an interval join of spans within a document, taken as running
nearest-neighbour windows over the sorted spans: no pairs are formed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.llm.shared import id_and_text, stored

SCOPE = 300
#: Fixed patterns of the base kinds: name, pattern, group that is measured, least length.
BASE = (
    ("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"(AKIA[A-Z0-9]+)", 1, 20),
    ("hex", r"([0-9a-f]+)", 1, 24),
)
#: What must be in a text before a base pattern is tried on it.
HINTS = (r"(?i:passw|secret|token|api_?key)", r"AKIA[A-Z0-9]{16}", r"[0-9a-f]{24}")
#: Weak kinds: name, pattern (its group 1 is the span), role.
WEAK = (
    ("account", r"""(?<![A-Za-z0-9])((?i:user(?:name)?|login|account|client_?id)["']?\x20*[:=]\x20*["']?[A-Za-z0-9._@-]{3,})""", "identifier"),
    ("random", r"(?<![A-Za-z0-9+/=_-])((?=[A-Za-z0-9+/]*[0-9])(?=[A-Za-z0-9+/]*[A-Z])(?=[A-Za-z0-9+/]*[a-z])[A-Za-z0-9+/]{32,}={0,2})(?![A-Za-z0-9+/=_-])", "secret"),
    ("endpoint", r"""((?:[a-z][a-z0-9+]{1,15}://[A-Za-z0-9._~%:@/?&=#-]+)|(?<![0-9.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?::[0-9]{2,5})?(?![0-9.]))""", "endpoint"),
)
ROLES = {"assign": "secret", "access": "identifier", "hex": "secret"} | {kind: role for kind, _, role in WEAK}
#: The order of kinds at one start.
RANK = {kind: i for i, kind in enumerate([*(b[0] for b in BASE), *(w[0] for w in WEAK)])}
SPAN = "array<struct<start:int,rank:int,end:int>>"


def spans_of(text: Column, pattern: str, group: int, least: int, rank: int) -> Column:
    """Spans of all matches, from the left, whose ``group`` has ``least`` code points or more.

    The text between matches and the matches themselves, laid end to end, give the positions.
    """
    between, found, measured = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    gaps = F.transform(F.slice(between, F.lit(1), F.size(found)), F.length)
    parts = F.zip_with(gaps, F.transform(found, F.length), lambda g, m: F.struct(g.alias("gap"), m.alias("size")))
    parts = F.zip_with(parts, F.transform(measured, F.length), lambda p, v: F.struct(p["gap"].alias("gap"), p["size"].alias("size"), v.alias("of")))
    empty = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

    def step(acc, p):
        start = acc["at"] + p["gap"]
        span = F.struct(start.alias("start"), F.lit(rank).alias("rank"), (start + p["size"]).alias("end"))
        return F.struct((start + p["size"]).alias("at"), F.when(p["of"] >= least, F.array_append(acc["out"], span)).otherwise(acc["out"]).alias("out"))

    return F.aggregate(parts, empty, step)["out"]


def base_spans(text: Column) -> list[Column]:
    """Spans of each base kind."""
    none = F.array().cast(SPAN)
    return [F.when(text.rlike(hint), spans_of(text, pattern, group, least, RANK[kind])).otherwise(none).alias(kind) for (kind, pattern, group, least), hint in zip(BASE, HINTS, strict=True)]


def weak_spans(text: Column) -> Column:
    none = F.array().cast(SPAN)
    return F.concat(*[F.when(text.rlike(pattern), spans_of(text, pattern, 1, 1, RANK[kind])).otherwise(none) for kind, pattern, _ in WEAK])


def shown(spans: Column) -> Column:
    """``kind:start:end`` of sorted spans, comma-joined."""
    names = F.array(*[F.lit(k) for k in RANK])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["rank"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def linked(found: DataFrame, scope: int = SCOPE) -> DataFrame:
    """``key, added``: the weak spans of ``found`` (``key, base, weak``) that other parts in their scope complete.

    An account needs a secret, a random token needs an identifier, an endpoint needs both. A weak span that overlaps a
    base span is part of that and not reported.
    """
    names = F.array(*[F.lit(ROLES[k]) for k in RANK])
    some = found.where(F.size("weak") > 0).where(F.size("base") + F.size("weak") > 1).dropDuplicates(["key"])
    rows = some.select("key", F.explode(F.concat("base", "weak")).alias("s")).select("key", "s.*", F.get(names, F.col("s.rank")).alias("role"))
    strong, fields = F.col("rank") < len(BASE), {}
    # nearest part of each role on either side: running extremes over the spans sorted by start
    before = W.partitionBy("key").orderBy("start", "rank", "end").rowsBetween(W.unboundedPreceding, -1)
    after = W.partitionBy("key").orderBy(F.desc("start"), F.desc("rank"), F.desc("end")).rowsBetween(W.unboundedPreceding, -1)
    for name, is_it in {"identifier": F.col("role") == "identifier", "secret": F.col("role") == "secret", "strong": strong}.items():
        fields |= {f"{name}_left": F.max(F.when(is_it, F.col("end"))).over(before), f"{name}_right": F.min(F.when(is_it, F.col("start"))).over(after)}
    rows = rows.withColumns(fields)

    def near(role: str) -> Column:
        left, right = F.col(f"{role}_left"), F.col(f"{role}_right")
        return F.coalesce(F.col("start") - left <= scope, F.lit(False)) | F.coalesce(right - F.col("end") <= scope, F.lit(False))

    apart = ~(F.coalesce(F.col("strong_left") > F.col("start"), F.lit(False)) | F.coalesce(F.col("strong_right") < F.col("end"), F.lit(False)))
    whole = F.when(F.col("role") == "identifier", near("secret")).when(F.col("role") == "secret", near("identifier")).otherwise(near("identifier") & near("secret"))
    kept = rows.where(~strong).where(apart & whole)
    return kept.groupBy("key").agg(F.collect_list(F.struct("start", "rank", "end")).alias("added"))


def scan(docs: DataFrame, scope: int = SCOPE) -> DataFrame:
    """``doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_added`` of every document.

    Positions are code points, ends exclusive; spans stand by start, then kind. A text without spans has the digest of
    the empty text and an empty list. Rows are scanned one by one, and told apart by 128 bits of a hash; null texts are empty.
    """
    text = F.col("text")
    kinds = [k for k, *_ in BASE]
    found = id_and_text(docs).select("doc_id", F.struct(F.xxhash64("doc_id", "text").alias("low"), F.xxhash64(F.lit(7), "text", "doc_id").alias("high")).alias("key"), *base_spans(text), weak_spans(text).alias("weak"))
    found = found.select("doc_id", "key", *[F.size(k).cast("long").alias(f"n_{k}") for k in kinds], F.array_sort(F.concat(*kinds)).alias("base"), "weak")
    found = stored(found, "spans")
    added = linked(found.select("key", "base", "weak"), scope).withColumnRenamed("key", "of")
    out = found.join(added, F.col("key") == F.col("of"), "left")
    every = F.array_sort(F.concat("base", F.coalesce("added", F.array().cast(SPAN))))
    return out.select("doc_id", *[f"n_{k}" for k in kinds], F.sha2(shown(F.col("base")), 256).alias("base_sha256"), shown(every).alias("spans"), F.coalesce(F.size("added"), F.lit(0)).cast("long").alias("n_added"))
