"""Toxicity by multiple-instance learning: sentences are instances, documents carry the labels.

A sentence's probability is a logistic function of the words in it; a document's
is the noisy-or of its sentences'. Training sees document labels only, yet yields
sentence scores, which locate the offending sentences.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.llm.shared import id_and_text, memory, over_slices, plain, returned, slices, strings

ENDS = r"[.!?\n]+"
#: Lengths of the beginnings of words that are features.
PREFIXES = range(3, 8)
#: Documents of the fit whose features are counted at once.
BLOCK_DOCUMENTS = 500
_edges = regex.compile(r"^[^\p{L}\p{N}]+|[^\p{L}\p{N}]+$")


@dataclass
class Settings:
    """Bounds of the fitted sample and of the fit; they don't touch scoring."""

    most_rows: int = 3000  # training documents of each label
    most_chars: int = 8_000  # longer documents aren't trained on
    most_features: int = 4000  # words and beginnings of words with a weight
    least_documents: int = 4  # training documents that a feature with a weight is in
    least_z: float = 2.0  # how surely it must tell the labels apart
    steps: int = 300
    l2: float = 2e-4
    threshold: float = 0.7


@dataclass
class Model:
    weights: dict[str, float]
    bias: float


def fold(word: str) -> str:
    return _edges.sub("", word.lower())


def held_out(doc_id) -> F.Column:
    """crc32 of the doc_id as text leaves 1 on division by 3; a null doc_id is held out never."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1, F.lit(False))


def sentence_words(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, list[str]]:
    """(document of each sentence, sentence of each word, word code, folded dictionary) of ``texts``; blank sentences are none."""
    lists = pc.split_pattern_regex(plain(texts), ENDS)
    doc = np.repeat(np.arange(len(texts)), np.diff(lists.offsets.to_numpy().astype(np.int64)))
    words = pc.utf8_split_whitespace(lists.flatten())
    coded = words.flatten().dictionary_encode()
    codes = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    at = np.repeat(np.arange(len(doc)), np.diff(words.offsets.to_numpy().astype(np.int64)))
    folded = [fold(w) for w in strings(coded.dictionary)]
    real = np.fromiter((bool(w) for w in folded), bool, len(folded))
    keep = real[codes] if len(codes) else np.zeros(0, bool)
    codes, at = codes[keep], at[keep]
    used, at = np.unique(at, return_inverse=True)
    return doc[used], at, codes, folded


def features(word: str) -> list[str]:
    """A word and its beginnings, so that inflected and compound forms share what their stem tells."""
    return [word, *("^" + word[:k] for k in PREFIXES if k < len(word))]


def _spread(groups: np.ndarray, codes: np.ndarray, lists: np.ndarray, flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(group, feature) pairs from (group, word) pairs; word ``i`` has the features ``flat[lists[i]:lists[i + 1]]``."""
    size = np.diff(lists)[codes]
    ends = np.cumsum(size)
    return np.repeat(groups, size), flat[np.arange(int(ends[-1]) if len(ends) else 0) + np.repeat(lists[codes] - ends + size, size)]


def fit(texts: list[str], labels: np.ndarray, row_weight: np.ndarray, s: Settings) -> Model:
    """Gradient descent on the noisy-or likelihood, over the features that tell the labels apart best."""
    if not len(texts) or labels.min() == labels.max():
        return Model({}, 30.0 if len(texts) and labels.min() == 1 else -30.0)
    doc, at, codes, folded = sentence_words(pa.array(texts, pa.string()))
    names = {w: i for i, w in enumerate(dict.fromkeys(folded))}
    codes = np.fromiter((names[w] for w in folded), np.int64, len(folded))[codes]
    pairs = np.unique(at * len(names) + codes)  # a word counts once in a sentence
    at, codes = pairs // len(names), pairs % len(names)
    known: dict[str, int] = {}
    per_word = [[known.setdefault(f, len(known)) for f in features(w)] for w in names]
    lists = np.r_[0, np.cumsum([len(x) for x in per_word])]
    flat = np.fromiter((f for x in per_word for f in x), np.int64, int(lists[-1]))
    in_docs = np.unique(doc[at] * len(names) + codes)
    df, pos, neg, seen = (np.zeros(len(known)) for _ in range(4))
    blocks = np.searchsorted(in_docs, np.arange(0, len(texts) + BLOCK_DOCUMENTS, BLOCK_DOCUMENTS) * len(names))
    for some in np.split(in_docs, blocks[1:-1]):  # a document's words stand together, and have many times as many features
        d, f = _spread(some // len(names), some % len(names), lists, flat)
        once = np.unique(d * len(known) + f)
        d, f = once // len(known), once % len(known)
        df += np.bincount(f, minlength=len(known))
        for of, y in ((pos, 1), (neg, 0)):
            of += np.bincount(f, weights=row_weight[d] * (labels[d] == y), minlength=len(known))
        seen += np.bincount(f, weights=labels[d] == 1, minlength=len(known))
    del in_docs, d, f, once
    all_pos, all_neg = (float((row_weight * (labels == y)).sum()) for y in (1, 0))
    a, b = (pos + 0.5) / (all_pos + 1), (neg + 0.5) / (all_neg + 1)
    z = np.abs(np.log(a / b)) / np.sqrt(1 / (seen + 0.5) + 1 / (df - seen + 0.5))
    z[df < s.least_documents] = 0
    best = np.argsort(-z, kind="stable")[: s.most_features]
    best = np.sort(best[z[best] > s.least_z])
    slot = np.full(len(known), -1)
    slot[best] = np.arange(len(best))
    kept = slot[flat] >= 0
    lists = np.r_[0, np.cumsum(kept)][lists]
    flat = slot[flat[kept]]
    at, codes = _spread(at, codes, lists, flat)
    n, m = len(doc), len(best)
    bias = np.log(max(all_pos / (all_pos + all_neg), 1e-4) / max(1.0, n / len(texts)))
    row_weight = row_weight / row_weight.sum()
    theta, first, second = np.r_[np.zeros(m), bias], np.zeros(m + 1), np.zeros(m + 1)
    for t in range(1, s.steps + 1):
        x = np.bincount(at, weights=theta[codes], minlength=n) + theta[m]
        soft = np.logaddexp(0, x)
        none = np.exp(-np.bincount(doc, weights=soft, minlength=len(texts)))  # probability that no sentence offends
        pull = np.where(labels == 1, -none / np.maximum(1 - none, 1e-9), 1.0) * row_weight
        g = pull[doc] / (1 + np.exp(-x))
        grad = np.r_[np.bincount(codes, weights=g[at], minlength=m) + s.l2 * theta[:m], g.sum()]
        first, second = 0.9 * first + 0.1 * grad, 0.999 * second + 0.001 * grad**2
        theta = theta - 0.1 * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-9)
    words = list(known)
    return Model({words[i]: float(x) for i, x in zip(best, theta[:m], strict=True)}, float(theta[m]))


def train(docs: DataFrame, labels: DataFrame, s: Settings | None = None) -> Model:
    """Fit on labelled documents that aren't held out: for each label the ``most_rows`` first by a hash of doc_id.

    Where a label has more rows, its sample counts for all of them. A doc_id with several labels counts as toxic if any
    says so; null labels are none. The sample is fitted in one task; only the model comes to the driver.
    """
    s = s or Settings()
    marked = labels.select(labels["doc_id"].cast("long").alias("doc_id"), labels["toxic"].cast("int").alias("y")).where("doc_id is not null and y is not null")
    marked = marked.groupBy("doc_id").agg(F.max("y").alias("y")).where(~held_out(F.col("doc_id")))
    counts = {r["y"]: r["n"] for r in marked.groupBy("y").agg(F.count("*").alias("n")).collect()}
    parts = [marked.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(s.most_rows) for y in (0, 1)]
    sample = F.broadcast(parts[0].union(parts[1]))  # at most 2 * most_rows ids
    rows = id_and_text(docs).where(F.length("text") <= s.most_chars).join(sample, "doc_id")

    def run(batches):
        memory("")  # what operators before this one have left in the worker
        held = sorted((r["doc_id"], r["text"], r["y"]) for b in batches for r in b.to_pylist())
        y = np.array([r[2] for r in held], np.int64)
        share = {k: counts[k] / max(1, int((y == k).sum())) for k in counts}
        model = fit([r[1] for r in held], y, np.array([share[k] for k in y.tolist()], float), s)
        yield pa.record_batch([pa.array([None, *model.weights], pa.string()), pa.array([model.bias, *model.weights.values()])], names=["feature", "weight"])
        del held, model
        returned()

    fitted = {r["feature"]: r["weight"] for r in rows.repartition(1).mapInArrow(run, "feature string, weight double").collect()}
    return Model({k: w for k, w in fitted.items() if k is not None}, fitted.get(None, -30.0))


def word_weights(model: Model, words) -> np.ndarray:
    """What each word adds to its sentence."""
    known = model.weights
    return np.fromiter((sum(known.get(f, 0.0) for f in features(w)) for w in words), float, len(words))


def _sentence_scores(texts: pa.Array, model: Model) -> tuple[np.ndarray, np.ndarray]:
    doc, at, codes, folded = sentence_words(texts)
    if len(codes):
        # spellings that fold to one word count once
        names: dict[str, int] = {}
        one = np.fromiter((names.setdefault(w, len(names)) for w in folded), np.int64, len(folded))
        weight = word_weights(model, names)
        telling = weight != 0
        codes = one[codes]
        keep = telling[codes]
        pairs = np.unique(at[keep] * len(names) + codes[keep])
        x = np.bincount(pairs // len(names), weights=weight[pairs % len(names)], minlength=len(doc)) + model.bias
    else:
        x = np.zeros(len(doc))
    return doc, x


def score(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """``doc_id, held_out, score, predicted, n_sentences, top_sentence, top_score`` of every document.

    ``top_sentence`` numbers the likeliest offending sentence from 0 (the first of equals). A text without words has
    score 0 and no top sentence.
    """

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        n = batch.num_rows
        doc, x = _sentence_scores(batch.column(1), model)
        p = 1 - np.exp(-np.bincount(doc, weights=np.logaddexp(0, x), minlength=n))
        count = np.bincount(doc, minlength=n)
        first = np.r_[0, np.cumsum(count)[:-1]]
        order = np.lexsort((np.arange(len(x)), -x, doc))
        top = np.where(count > 0, order[np.minimum(first, max(0, len(x) - 1))] if len(x) else 0, 0)
        none = count == 0
        best = 1 / (1 + np.exp(-x[top])) if len(x) else np.zeros(n)
        return pa.record_batch(
            [batch.column(0), pa.array(p), pa.array(count, pa.int64()), pa.array(top - first, pa.int64(), mask=none), pa.array(best, mask=none)],
            names=["doc_id", "score", "n_sentences", "top_sentence", "top_score"],
        )

    scored = over_slices(id_and_text(docs), kernel, "doc_id long, score double, n_sentences long, top_sentence long, top_score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "n_sentences", "top_sentence", "top_score")


def offending_sentences(docs: DataFrame, model: Model, least: float = 0.5) -> DataFrame:
    """``doc_id, sentence, score, text`` of every sentence with a score of ``least`` or more, numbered as in ``score``."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        doc, x = _sentence_scores(batch.column(1), model)
        p = 1 / (1 + np.exp(-x))
        hits = np.flatnonzero(p >= least)
        number = np.arange(len(doc)) - np.searchsorted(doc, doc)
        kept: dict[int, list[str]] = {}
        for d in set(doc[hits].tolist()):
            kept[d] = [t for t in regex.split(ENDS, batch.column(1)[d].as_py()) if any(fold(w) for w in t.split())]
        ids = batch.column(0)
        rows = [(ids[int(doc[i])].as_py(), int(number[i]), float(p[i]), kept[int(doc[i])][int(number[i])].strip()) for i in hits]
        names = ["doc_id", "sentence", "score", "text"]
        return pa.record_batch([pa.array(list(c), t) for c, t in zip(zip(*rows, strict=True) if rows else [[]] * 4, [pa.int64(), pa.int64(), pa.float64(), pa.string()], strict=True)], names=names)

    return over_slices(id_and_text(docs), kernel, "doc_id long, sentence long, score double, text string")


def without_toxic(docs: DataFrame, model: Model, threshold: float = 0.7) -> DataFrame:
    """The rows of ``docs`` that the model scores below ``threshold``, with their columns; a row without doc_id stays or goes by its text too."""

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        doc, x = _sentence_scores(pc.fill_null(batch.column(where), ""), model)
        p = 1 - np.exp(-np.bincount(doc, weights=np.logaddexp(0, x), minlength=batch.num_rows))
        return batch.filter(pa.array(p < threshold))

    where = docs.columns.index("text")

    def run(batches):
        memory("")
        for part in slices(batches, column=where):
            yield kernel(part)
        returned()

    return docs.mapInArrow(run, docs.schema)
