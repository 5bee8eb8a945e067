"""Scores of documents by the difference of two language models' cross-entropies per token.

A target model (documents that labels mark as good) and a background model (all documents) are interpolated bigram
models of the same form, smoothing and vocabulary. The vocabulary holds every word that occurs ``least_count`` times or
more, so it grows with the corpus; the rest (by default words seen once) are one unknown word in both models.

Neither words nor bigrams are collected or broadcast. Documents are dealt to chunks of bounded size. A chunk sends its
sorted word hashes with their counts, packed by ranges of hashes, to buckets that sum them over all chunks; a bucket
answers in the order of the question with the words' common ids. The counts of words and bigrams go the same way.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.llm.shared import SLICE_BYTES, id_and_text, slices, stored, strings, word_codes

LEAST_COUNT = 2
PRIOR = 50.0
#: Words of a chunk (its last document may exceed it).
CHUNK_WORDS = 1 << 20
#: Keys of all chunks that are summed together, about.
BUCKET_KEYS = 1 << 20
#: What stands before a document's first word; ids of words are below.
START = (1 << 31) - 1
#: Added to the keys of words; those of bigrams are below.
WORD = 1 << 62
QUESTIONS = "chunk long, bucket long, n long, blob binary"


def _hashed(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(document position, hash) of each lower-case word."""
    where, codes, words = word_codes(texts)
    each = np.fromiter((xxhash.xxh3_64_intdigest(w.lower()) for w in strings(words)), np.uint64, len(words)).view(np.int64)
    return where, each[codes]


def summed(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(distinct keys, how often each)."""
    if not len(keys):
        return keys, np.zeros(0, np.int64)
    keys = np.sort(keys)
    start = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    return keys[start], np.diff(np.r_[start, len(keys)])


def packed(*columns: np.ndarray) -> bytes:
    """Columns of 64-bit integers, compressed byte by byte."""
    raw = np.stack([c.astype(np.int64) for c in columns])
    raw = np.ascontiguousarray(raw.view(np.uint8).reshape(-1, 8).T).tobytes()
    return len(raw).to_bytes(8, "little") + pa.compress(raw, "zstd", asbytes=True)


def unpacked(blob: bytes, width: int) -> np.ndarray:
    """The columns that ``packed`` took, as rows of an array."""
    raw = pa.decompress(blob[8:], int.from_bytes(blob[:8], "little"), "zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, -1).T).view(np.int64).reshape(width, -1)


def chunked(docs: DataFrame) -> DataFrame:
    """``chunk, doc_id, n, ids, words`` of every document, written once: its ``n`` words as numbers (uint32, byte by byte) of the chunk's own
    list. The list is one more row a chunk, in which ``words`` holds ``n`` sorted hashes and counts; elsewhere that is null.
    """

    def run(batches):
        chunk, held, rows, words = TaskContext.get().partitionId() << 32, [], [], 0

        def flush():
            known, codes, n = np.unique(np.concatenate(held), return_inverse=True, return_counts=True)
            codes = codes.astype("<u4")
            at = 0
            for ids, sizes in rows:
                ends = at + np.cumsum(sizes)
                blobs = [codes[a:b].view(np.uint8).reshape(-1, 4).T.tobytes() for a, b in zip([at, *ends[:-1].tolist()], ends.tolist(), strict=True)]
                at = int(ends[-1])
                yield batch_of(ids, sizes, blobs, [None] * len(ids))
            yield batch_of(pa.nulls(1, pa.int64()), [len(known)], [None], [packed(np.diff(known, prepend=0), n)])
            held.clear()
            rows.clear()
            pa.default_memory_pool().release_unused()

        def batch_of(ids, sizes, blobs, lists):
            return pa.record_batch([pa.array([chunk] * len(ids), pa.int64()), ids, pa.array(sizes, pa.int64()), pa.array(blobs, pa.binary()), pa.array(lists, pa.binary())], names=["chunk", "doc_id", "n", "ids", "words"])

        for batch in slices(batches, most=SLICE_BYTES // 4):
            where, hashes = _hashed(batch.column(1))
            held.append(hashes)
            # a column of the batch would keep the whole batch
            rows.append((pa.array(batch.column(0).to_pylist(), pa.int64()), np.bincount(where, minlength=batch.num_rows)))
            words += len(hashes)
            if words >= CHUNK_WORDS:
                yield from flush()
                chunk, words = chunk + 1, 0
        if rows:
            yield from flush()

    return stored(id_and_text(docs).mapInArrow(run, "chunk long, doc_id long, n long, ids binary, words binary"), "chunks")


def asked(chunk: int, key: np.ndarray, counts: list[np.ndarray], buckets: int) -> list[tuple[int, int, int, bytes]]:
    """Rows of QUESTIONS: sorted keys and their counts, by the bucket of their range."""
    bucket = np.minimum(((key * 2.0**-64 + 0.5) * buckets).astype(np.int64), buckets - 1)
    cuts = [0, *(np.flatnonzero(np.diff(bucket)) + 1).tolist(), len(key)]
    return [(chunk, int(bucket[i]), j - i, packed(np.diff(key[i:j], prepend=0), *[c[i:j] for c in counts])) for i, j in zip(cuts, cuts[1:], strict=False) if i < j]


def as_questions(rows: list[tuple[int, int, int, bytes]]) -> pa.Table:
    columns = list(zip(*rows, strict=True)) if rows else [[]] * 4
    return pa.table([pa.array(list(c), t) for c, t in zip(columns, [pa.int64()] * 3 + [pa.binary()], strict=True)], names=["chunk", "bucket", "n", "blob"])


def answered(questions: DataFrame, width: int, of_sums) -> DataFrame:
    """QUESTIONS with what ``of_sums(bucket, sums)`` makes of the sums of each key over all chunks, in the order of the question's keys."""

    def run(held: pa.Table) -> pa.Table:
        sizes = held["n"].to_pylist()
        parts = [unpacked(blob, width + 1) for blob in held["blob"].to_pylist()]
        key, place = np.unique(np.concatenate([np.cumsum(p[0]) for p in parts]), return_inverse=True)
        each = np.concatenate(parts, axis=1)
        sums = [np.bincount(place, weights=each[i + 1], minlength=len(key)).astype(np.int64) for i in range(width)]
        values = [v[place] for v in of_sums(held["bucket"][0].as_py(), sums)]
        ends = np.cumsum(sizes)
        blobs = [packed(*[v[e - n : e] for v in values]) for e, n in zip(ends.tolist(), sizes, strict=True)]
        return held.select(["chunk", "bucket", "n"]).append_column("blob", pa.array(blobs, pa.binary()))

    return questions.groupBy("bucket").applyInArrow(run, QUESTIONS)


def vocabulary(chunks: DataFrame, least_count: int = LEAST_COUNT, least_share: float = 0.0) -> tuple[DataFrame, int]:
    """Ids of the chunks' words (as QUESTIONS; 0: unknown), and how many words are known: those that occur ``least_count`` times and have ``least_share`` of all tokens."""
    sizes = chunks.groupBy(F.col("words").isNull().alias("of_document")).agg(F.sum("n").alias("n")).collect()  # two rows
    n = {r["of_document"]: r["n"] for r in sizes}
    least = max(least_count, least_share * n.get(True, 0))
    buckets = 1 + n.get(False, 0) // BUCKET_KEYS

    def ask(batches):
        for batch in batches:
            for chunk, blob in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                word, count = unpacked(blob, 2)
                yield from as_questions(asked(chunk, np.cumsum(word), [count], buckets)).to_batches()

    def ids(bucket, sums):
        known = sums[0] >= least
        found = np.where(known, 1 + bucket + buckets * (np.cumsum(known) - 1), 0)
        if found.max(initial=0) >= START:
            raise ValueError("more words than ids")
        return [found, np.full(len(found), known.sum())]

    questions = chunks.where("words is not null").select("chunk", "words").mapInArrow(ask, QUESTIONS)
    found = stored(answered(questions, 1, ids), "words")

    def size(batches):
        for batch in batches:
            rows = {b: int(unpacked(x, 2)[1][0]) for b, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)}
            yield pa.record_batch([pa.array(list(rows), pa.int64()), pa.array(list(rows.values()), pa.int64())], names=["bucket", "n"])

    known = found.select("bucket", "blob").mapInArrow(size, "bucket long, n long").distinct().agg(F.sum("n")).first()[0]
    return found, known or 0


def mixed(key: np.ndarray) -> np.ndarray:
    """One to one, such that ranges of the result are about equally filled."""
    key = key.astype(np.uint64)
    for _ in range(2):
        key = (key ^ (key >> np.uint64(32))) * np.uint64(0x9E3779B97F4A7C15)
    return (key ^ (key >> np.uint64(29))).view(np.int64)


def read_chunk(held: pa.Table, known: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[np.ndarray]]:
    """(document position, bigram) of each word of a chunk, and its sorted keys with their counts in all documents and in those of the target, then how often they end one, in the same way."""
    words = known.filter(pc.equal(known["kind"], 0)).sort_by("bucket")
    ids = np.concatenate([np.zeros(0, np.int64), *[unpacked(x, 2)[0] for x in words["blob"].to_pylist()]])
    good = pc.is_in(held["doc_id"], value_set=known.filter(pc.equal(known["kind"], 1))["n"].combine_chunks()).to_numpy()
    blobs = held["ids"].to_pylist()
    n = np.fromiter((len(b) for b in blobs), np.int64, len(blobs)) // 4
    codes = [np.zeros((0, 4), np.uint8), *[np.frombuffer(b, np.uint8).reshape(4, -1).T for b in blobs]]
    word = ids[np.ascontiguousarray(np.concatenate(codes)).view("<u4").ravel()]
    where = np.repeat(np.arange(len(blobs)), n)
    ends = np.cumsum(n)[n > 0]
    first, last = (np.cumsum(n) - n)[n > 0], word[ends - 1]
    before = np.r_[START, word[:-1]] if len(word) else word
    before[first] = START
    gram = (before << 31) | word
    each, last = mixed(np.concatenate([gram, WORD | word, np.full(len(first), WORD | START)])), mixed(WORD | last)
    of_target = np.concatenate([good[where], good[where], good[n > 0]])
    key, count = summed(each)
    counts = [count]
    for keys in (each[of_target], last, last[good[n > 0]]):
        of, count = summed(keys)
        counts.append(np.zeros(len(key), np.int64))
        counts[-1][np.searchsorted(key, of)] = count
    return where, gram, key, counts


def score(docs: DataFrame, target_ids: DataFrame, least_share: float = 0.0, prior: float = PRIOR, least_count: int = LEAST_COUNT) -> DataFrame:
    """``doc_id, n_words, target_loss, background_loss, difference`` of every document.

    p(word | before) = (count(before, word) + prior * p(word)) / (count(before) + prior), with p(word) add-one smoothed
    over the shared vocabulary. Each document counts in the background, those of ``target_ids`` in the target too.
    Losses are nats per word; ``difference`` = target - background, lower: more like the target. Documents without words
    have null losses. Rows of equal doc_id are scored each; null doc_ids are never of the target.
    """
    target_ids = target_ids.select(target_ids["doc_id"].cast("long").alias("doc_id")).where("doc_id is not null").distinct()
    chunks = chunked(docs)
    words, known = vocabulary(chunks, least_count, least_share)
    size = known + 2
    rows = chunks.where("words is null").select("chunk", "doc_id", "ids")
    good = stored(chunks.where("words is null").select("chunk", "doc_id", "n").join(target_ids, "doc_id"), "target")
    n_background = chunks.where("words is null").agg(F.sum("n")).first()[0] or 0
    n_target = good.agg(F.sum("n")).first()[0] or 0
    buckets = 1 + 2 * n_background // BUCKET_KEYS
    resolved = words.select("chunk", F.lit(0).alias("kind"), "bucket", "n", "blob")
    resolved = resolved.union(good.select("chunk", F.lit(1), F.lit(0).cast("long"), "doc_id", F.lit(None).cast("binary")))

    def ask(held: pa.Table, known: pa.Table) -> pa.Table:
        if not held.num_rows:
            return as_questions([])
        _, _, key, counts = read_chunk(held, known)
        return as_questions(asked(held["chunk"][0].as_py(), key, counts, buckets))

    def scored(held: pa.Table, known: pa.Table) -> pa.Table:
        where, gram, key, _ = read_chunk(held, known)
        answers = known.filter(pc.equal(known["kind"], 2)).sort_by("bucket")
        sums = np.concatenate([np.zeros((4, 0), np.int64), *[unpacked(x, 4) for x in answers["blob"].to_pylist()]], axis=1)
        gram, of = np.unique(gram, return_inverse=True)

        def counts(of_key: np.ndarray) -> np.ndarray:
            return sums[:, np.searchsorted(key, mixed(of_key))]

        before, word = gram >> 31, gram & START
        pair, one, context = counts(gram), counts(WORD | word), counts(WORD | before)
        context = context[:2] - context[2:]
        count = np.bincount(where, minlength=held.num_rows)
        none = count == 0
        losses = []
        for i, n in ((1, n_target), (0, n_background)):
            p = (one[i] + 1) / (n + size)
            x = -np.log((pair[i] + prior * p) / (context[i] + prior))
            losses.append(np.bincount(where, weights=x[of], minlength=held.num_rows) / np.maximum(count, 1))
        t, b = losses
        return pa.table({"doc_id": held["doc_id"], "n_words": count.astype(np.int64), "target_loss": pa.array(t, mask=none), "background_loss": pa.array(b, mask=none), "difference": pa.array(t - b, mask=none)})

    questions = rows.groupBy("chunk").cogroup(resolved.groupBy("chunk")).applyInArrow(ask, QUESTIONS)
    answers = answered(questions, 4, lambda _, sums: sums).select("chunk", F.lit(2), "bucket", "n", "blob")
    return rows.groupBy("chunk").cogroup(resolved.union(answers).groupBy("chunk")).applyInArrow(scored, "doc_id long, n_words long, target_loss double, background_loss double, difference double")
