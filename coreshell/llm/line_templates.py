"""Line dedup by a log-template tree of fixed depth, with DataFrame and SQL functions only.

A line goes down the tree by its number of tokens; a token with a digit is a variable field. At a leaf, lines with the
same fixed tokens have one template. Templates that recur show further variable fields: each line also stands under
general templates, in which one stretch of its tokens is variable whatever it holds. In lines of four tokens or more
that is the first, middle or last third, so that names, words and paths anywhere, the leading tokens included, are
generalised; in lines of twelve or more also the last half, or all but the leading tokens and the last half. A template
that as many lines of different documents share is one line with its varying stretch generalised. Lines whose template
recurs across documents are dropped.

Templates are told apart by 63 bits of a hash: among 10^11 lines and 10^9 recurring templates some ten lines would go by
accident.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coreshell.llm.shared import id_and_text, stored

LEAST_TOKENS = 4  # shorter lines have no general templates, and need as many documents as those
DEPTH = 2  # leading tokens that the template of the last half keeps
GENERAL_TOKENS = 12  # lines of as many tokens have templates with half of them variable
LEAST_DOCUMENTS = 2  # a template recurs if it is in as many documents
GENERAL_DOCUMENTS = 5  # a general one, or that of a short line, needs more
SPACE = r"\x09-\x0D\x20"
VARIABLE = rf"[^{SPACE}0-9]*[0-9][^{SPACE}]*"


def tokens(line: Column) -> Column:
    """Tokens of a line, those with a digit as ``<*>``."""
    masked = F.when(line.rlike("[0-9]"), F.regexp_replace(line, VARIABLE, "<*>")).otherwise(line)
    return F.filter(F.split(masked, f"[{SPACE}]+"), lambda t: t != "")


def template_keys(toks: Column) -> Column:
    """The keys of a line's templates, none for a line without tokens; the last bit tells that a template needs more documents."""
    n = F.size(toks)
    half, one, two = F.floor(n / 2).cast("int"), F.floor(n / 3).cast("int"), F.floor(n * 2 / 3).cast("int")

    def part(start: Column, size: Column) -> Column:
        return F.xxhash64(F.array_join(F.slice(toks, start, size), " "))

    thirds = [part(F.lit(1), one), part(one + 1, two - one), part(two + 1, n - two)]
    whole = F.shiftleft(F.xxhash64(F.lit(0), n, *thirds), 1)
    tail = F.xxhash64(F.array_join(F.slice(toks, F.lit(1), F.lit(DEPTH)), " "), part(n - half + 1, half))
    general = [F.when(n >= LEAST_TOKENS, F.xxhash64(F.lit(k), n, *[x for i, x in enumerate(thirds, 1) if i != k])) for k in (1, 2)]
    general += [F.when(n >= GENERAL_TOKENS, F.xxhash64(F.lit(4), n, part(F.lit(1), n - half))).when(n >= LEAST_TOKENS, F.xxhash64(F.lit(3), n, *thirds[:2]))]
    general += [F.when(n >= GENERAL_TOKENS, F.xxhash64(F.lit(5), n, tail))]
    more = lambda x: F.shiftleft(x, 1).bitwiseOR(F.lit(1).cast("long"))
    return F.when(n > 0, F.array_compact(F.array(F.when(n >= LEAST_TOKENS, whole).otherwise(whole.bitwiseOR(F.lit(1).cast("long"))), *map(more, general)))).otherwise(F.array().cast("array<bigint>"))


def _row(docs: DataFrame) -> DataFrame:
    """``doc_id, text`` and a key of both in 128 bits; repeated rows share theirs, and all that follows from it."""
    return id_and_text(docs).withColumn("row", F.struct(F.xxhash64("doc_id", "text").alias("low"), F.xxhash64(F.lit(7), "text", "doc_id").alias("high")))


def keyed_lines(docs: DataFrame) -> DataFrame:
    """``row, keys``: for each document its lines' template keys, in order."""
    lines = F.transform(F.split("text", "\n", -1), tokens)
    return _row(docs).select("row", F.transform(lines, template_keys).alias("keys"))


def recurring(keyed: DataFrame) -> DataFrame:
    """``key`` of the templates that recur; each document counts once."""
    each = keyed.select(F.explode(F.array_distinct(F.flatten("keys"))).alias("key"))
    few = F.col("key").bitwiseAND(F.lit(1).cast("long")) == 0
    return each.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") >= F.when(few, LEAST_DOCUMENTS).otherwise(GENERAL_DOCUMENTS)).select("key")


def drop_recurring(docs: DataFrame) -> DataFrame:
    """``doc_id, n_lines, n_dropped, text`` of every document, without the lines of recurring templates.

    Lines end at line feeds; the empty (or null) text is one empty line. Every copy of a recurring line goes, so exact
    copies should be removed before. Repeated rows are documents of their own.
    """
    keyed = stored(keyed_lines(docs), "line_keys")
    often = recurring(keyed)
    places = keyed.select("row", F.posexplode("keys").alias("line", "key")).select("row", "line", F.explode("key").alias("key"))
    gone = places.join(often, "key", "left_semi").groupBy("row").agg(F.collect_set("line").alias("gone")).withColumnRenamed("row", "of")
    out = _row(docs).join(gone, F.col("row") == F.col("of"), "left")
    lines, none = F.split("text", "\n", -1), F.size("gone") < 1
    left = F.filter(lines, lambda x, i: ~F.array_contains("gone", i))
    return out.select(
        "doc_id",
        F.size(lines).cast("long").alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("n_dropped"),
        F.when(F.col("gone").isNull() | none, F.col("text")).otherwise(F.array_join(left, "\n")).alias("text"),
    )


def _sql_keys() -> str:
    """The templates themselves: 0 needs few documents, the others more."""
    n = "len(toks)"
    half, one, two = f"({n} // 2)", f"({n} // 3)", f"({n} * 2 // 3)"
    parts = [f"toks[1:{one}]", f"toks[{one} + 1:{two}]", f"toks[{two} + 1:{n}]"]

    def text(kind: int, *some: str) -> str:
        return f"'{kind} ' || {n} || ' ' || " + " || chr(10) || ".join(f"array_to_string({x}, ' ')" for x in some)

    front, back = text(4, f"toks[1:{n} - {half}]"), text(5, f"toks[1:{DEPTH}]", f"toks[{n} - {half} + 1:{n}]")
    return f"""[
        CASE WHEN {n} >= {LEAST_TOKENS} THEN {text(0, "toks")} WHEN {n} > 0 THEN {text(6, "toks")} END,
        CASE WHEN {n} >= {LEAST_TOKENS} THEN {text(1, *parts[1:])} END,
        CASE WHEN {n} >= {LEAST_TOKENS} THEN {text(2, parts[0], parts[2])} END,
        CASE WHEN {n} >= {GENERAL_TOKENS} THEN {front} WHEN {n} >= {LEAST_TOKENS} THEN {text(3, *parts[:2])} END,
        CASE WHEN {n} >= {GENERAL_TOKENS} THEN {back} END]"""


#: The same rows in DuckDB's SQL, by the templates themselves.
ORACLE_SQL = f"""
WITH numbered AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
lines AS (SELECT r, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM numbered),
split AS (SELECT r, i, list_filter(string_split_regex(regexp_replace(line, '{VARIABLE}', '<*>', 'g'), '[{SPACE}]+'), lambda t: t <> '') AS toks FROM lines),
keys AS (SELECT DISTINCT r, i, unnest({_sql_keys()}) AS key FROM split),
often AS (SELECT key FROM keys WHERE key IS NOT NULL GROUP BY key
          HAVING count(DISTINCT r) >= CASE WHEN key[1] = '0' THEN {LEAST_DOCUMENTS} ELSE {GENERAL_DOCUMENTS} END),
gone AS (SELECT DISTINCT r, i FROM keys WHERE key IN (SELECT key FROM often)),
kept AS (SELECT l.r, count(*) AS n_lines, count(g.i) AS n_dropped, string_agg(l.line, chr(10) ORDER BY l.i) FILTER (WHERE g.i IS NULL) AS text
         FROM lines l LEFT JOIN gone g ON g.r = l.r AND g.i = l.i GROUP BY l.r)
SELECT doc_id, CAST(n_lines AS BIGINT) AS n_lines, CAST(n_dropped AS BIGINT) AS n_dropped, coalesce(kept.text, '') AS text
FROM numbered JOIN kept USING (r)
"""
