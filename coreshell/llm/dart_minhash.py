"""Near-duplicate classes by weighted signatures of hashed darts.

A document is a weighted set: its shingles of five words, each weighing as often as it occurs. Element and weight
span cells of unit area; on every cell falls a Poisson process of darts along the rank axis, drawn from the cell's hash
alone, so equal cells get equal darts in all documents. Each dart names a coordinate; a coordinate keeps its earliest
dart. Two documents agree in a coordinate with the probability of their weighted Jaccard similarity. Only ranks that a
document of its weight needs are drawn (some eight darts a coordinate, however long the text), and further ones where
a coordinate stays empty.

Signatures are joined by bands, candidates are verified by their exact weighted Jaccard similarity, and classes are
the connected components of verified links. A bucket of a band isn't expanded into pairs. Its members are compared with
one hub, the most popular of them. Two members that are both near the hub are of one class anyway. A member f that is
not near the hub H can only be near another member x if the two share something H doesn't explain, by the prefix
filter: what f and x have in common beyond what each has in common with H must lie outside H, and of two sets that share
m elements all but the last m - 1 in a common order meet. Where nothing outside H is needed, x is smaller than H by a
margin, and prefixes with H's shingles last must meet. So the rest is an exact join on such tokens, rare ones first, and
only where they meet across components.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.llm.shared import id_and_text, over_slices, slices, stored, strings, word_codes

BANDS, ROWS = 20, 5
#: Bytes of text that are signed together; a dart takes more memory than its word.
SIGNED_BYTES = 4 << 20
SHINGLE = 5
LIKENESS = 0.8
_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB)]


def mixed(x: np.ndarray) -> np.ndarray:
    """Spread 64 bits (the finaliser of the public splitmix64 generator)."""
    x = x + _MIX[0]
    x = (x ^ (x >> np.uint64(30))) * _MIX[1]
    x = (x ^ (x >> np.uint64(27))) * _MIX[2]
    return x ^ (x >> np.uint64(31))


def word_hashes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(document position, hash) of each lower-case word."""
    where, codes, words = word_codes(texts)
    each = np.fromiter((xxhash.xxh3_64_intdigest(w.lower()) for w in strings(words)), np.uint64, len(words))
    return where, each[codes]


def shingles(where: np.ndarray, words: np.ndarray, n: int) -> np.ndarray:
    """Sorted keys (document position in the upper 20 bits, shingle hash in the lower 44) of all shingles of ``n`` documents.

    A text of fewer words than a shingle has is one shingle.
    """
    count = np.bincount(where, minlength=n)
    first = np.cumsum(count) - count
    padded = np.concatenate([words, np.zeros(SHINGLE, np.uint64)])
    last = (first + count)[where]
    at = np.arange(len(words))
    total = np.zeros(len(words), np.uint64)
    for i in range(SHINGLE):
        total = mixed(total ^ np.where(at + i < last, padded[at + i], np.uint64(i + 1)))
    real = (at + SHINGLE <= last) | (at == first[where])
    return np.sort(where[real].astype(np.uint64) << np.uint64(44) | total[real] >> np.uint64(20))


def signatures(keys: np.ndarray, n: int, coordinates: int = BANDS * ROWS) -> tuple[np.ndarray, np.ndarray]:
    """(n x coordinates earliest darts, whether a document has any shingle)."""
    doc = (keys >> np.uint64(44)).astype(np.int64)
    fresh = np.r_[True, keys[1:] != keys[:-1]] if len(keys) else np.zeros(0, bool)
    index = np.arange(len(keys))
    copy = index - np.maximum.accumulate(np.where(fresh, index, 0)) if len(keys) else index
    cell = mixed(keys & np.uint64((1 << 44) - 1) ^ mixed(copy.astype(np.uint64)))
    weight = np.bincount(doc, minlength=n)
    earliest = np.full(n * coordinates, np.inf)
    dart = np.zeros(n * coordinates, np.uint64)
    low = np.zeros(n)
    high = np.where(weight > 0, coordinates * (np.log(coordinates) + 3) / np.maximum(weight, 1), 0.0)
    lacking = weight > 0
    while lacking.any():
        some = lacking[doc]
        seed, where, rank = cell[some], doc[some], np.zeros(int(some.sum()))
        while len(seed):
            seed = mixed(seed)
            rank = rank - np.log(((seed >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53)
            keep = rank <= high[where]
            seed, where, rank = seed[keep], where[keep], rank[keep]
            new = rank > low[where]
            slot = where[new] * coordinates + (mixed(seed[new] ^ _MIX[1]) % np.uint64(coordinates)).astype(np.int64)
            before = earliest[slot]
            np.minimum.at(earliest, slot, rank[new])
            won = (rank[new] == earliest[slot]) & (rank[new] < before)
            dart[slot[won]] = seed[new][won]
        empty = np.isinf(earliest).reshape(n, coordinates).any(1) & (weight > 0)
        low, high, lacking = np.where(empty, high, low), np.where(empty, 2 * high, high), empty
    return dart.reshape(n, coordinates), weight > 0


def band_hashes(darts: np.ndarray) -> np.ndarray:
    """A hash of each band of each signature."""
    n = len(darts)
    parts = darts.reshape(n, BANDS, ROWS)
    out = np.zeros((n, BANDS), np.uint64)
    for i in range(ROWS):
        out = mixed(out ^ parts[:, :, i])
    return out.view(np.int64)


def _signed(batch: pa.RecordBatch) -> pa.RecordBatch:
    n = batch.num_rows
    where, words = word_hashes(batch.column(1))
    ends = np.cumsum(np.bincount(where, minlength=n))
    data = words.tobytes()
    digests = np.frombuffer(b"".join(xxhash.xxh3_128_digest(data[8 * a : 8 * b]) for a, b in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)), ">i8").reshape(n, 2).astype(np.int64)
    darts, real = signatures(shingles(where, words, n), n)
    bands = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(np.where(real, BANDS, 0))].astype(np.int32)), pa.array(band_hashes(darts)[real].ravel()))
    return pa.record_batch([batch.column(0), pa.array(digests[:, 0]), pa.array(digests[:, 1]), bands], names=["doc_id", "high", "low", "bands"])


def signed(docs: DataFrame) -> DataFrame:
    """``doc_id``, the 128-bit digest of its words (``high``, ``low``) and its band hashes (none without words)."""
    return over_slices(id_and_text(docs), _signed, "doc_id long, high long, low long, bands array<long>", SIGNED_BYTES)


def _vectors(batch: pa.RecordBatch) -> pa.RecordBatch:
    n = batch.num_rows
    where, words = word_hashes(batch.column(1))
    keys = shingles(where, words, n)
    bounds = np.searchsorted(keys, np.arange(n + 1).astype(np.uint64) << np.uint64(44))
    short = (keys >> np.uint64(12)).astype(np.uint32)  # sorted within a document
    data = [short[a:b].tobytes() for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True)]
    return pa.record_batch([batch.column(0), pa.array(data, pa.binary())], names=["node", "vector"])


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Weighted Jaccard similarity of two sorted multisets."""
    if not len(a) or not len(b):
        return 1.0 if len(a) == len(b) else 0.0
    common = len(np.intersect1d(_numbered(a), _numbered(b), assume_unique=True))
    return common / (len(a) + len(b) - common)


def _numbered(sorted_values: np.ndarray) -> np.ndarray:
    """Distinct keys for the copies in a sorted multiset: value, then number of the copy."""
    index = np.arange(len(sorted_values))
    fresh = np.r_[True, sorted_values[1:] != sorted_values[:-1]] if len(index) else np.zeros(0, bool)
    return sorted_values.astype(np.int64) << 20 | index - np.maximum.accumulate(np.where(fresh, index, 0))


def _compared(least: float):
    """Arrow kernel: of ``a, b, of_a, of_b`` the sizes, what is common, a's shingles outside b (``own``) and, where those don't fill a's prefix, the first inside b (``inner``)."""

    def run(batches):
        for whole in batches:
            for batch in slices(iter([whole]), column=2):
                rows = []
                for of_a, of_b in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                    a, b = (_numbered(np.frombuffer(x, np.uint32)) for x in (of_a, of_b))
                    at = np.minimum(np.searchsorted(b, a), max(0, len(b) - 1))
                    inside = b[at] == a if len(b) else np.zeros(len(a), bool)
                    prefix = int((1 - least) * len(a) + 1e-9) + 1
                    own = a[~inside]
                    rows.append((len(a), len(b), len(a) - len(own), own, a[inside][: max(0, prefix - len(own))]))
                n_a, n_b, common, own, inner = zip(*rows, strict=True)
                lists = [pa.array(x, pa.list_(pa.int64())) for x in (own, inner)]
                yield pa.record_batch([batch.column(0), batch.column(1), *[pa.array(x, pa.int64()) for x in (n_a, n_b, common)], *lists], names=["a", "b", "n_a", "n_b", "common", "own", "inner"])

    return run


COMPARED = "a long, b long, n_a long, n_b long, common long, own array<long>, inner array<long>"


def components(links: DataFrame) -> DataFrame:
    """``node, label`` of every node in ``links`` (``a``, ``b``): the smallest node of its connected component.

    Smallest labels travel along links and then jump to their own label; each round is written to the shared folder.
    """
    both = stored(links.select("a", "b").union(links.select("b", "a")).distinct(), "both")
    state = stored(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("label")), "labels")
    while True:
        near = both.join(state, both["b"] == state["node"]).groupBy("a").agg(F.min("label").alias("near"))
        step = state.join(near, state["node"] == near["a"]).select("node", F.col("label").alias("old"), F.least("label", "near").alias("mid"))
        jump = state.select(F.col("node").alias("at"), F.col("label").alias("far"))
        step = step.join(jump, step["mid"] == jump["at"], "left").select("node", "old", F.least("mid", F.coalesce("far", "mid")).alias("label"))
        step = stored(step, "labels")
        if step.where("label < old").isEmpty():
            return step.select("node", "label")
        state = step.select("node", "label")


def near_duplicates(docs: DataFrame, least: float = LIKENESS) -> DataFrame:
    """``doc_id, class_id, class_size`` of every document; ``class_id`` is the smallest doc_id of its class.

    Documents with the same words (in any case and spacing) are one class at once; texts without words are such a class.
    Classes joined by a chain of links of weighted Jaccard similarity ``least`` or more are one. Rows of equal doc_id
    count as one document; rows without doc_id are matched as copies only, and have no class_id where all of a class lack one.
    """
    rows = stored(signed(docs), "signatures")
    nodes = stored(rows.groupBy("high", "low").agg(F.min("doc_id").alias("node"), F.first("bands").alias("bands"), F.count("*").alias("n")), "nodes")
    dealt = nodes.where("node is not null").select("node", F.posexplode("bands").alias("band", "hash"))
    shared = dealt.groupBy("band", "hash").agg(F.count("*").alias("n")).where("n > 1")
    shared = stored(dealt.join(shared, ["band", "hash"]), "shared")
    labels = _joined(docs, shared, least)
    if labels is None:
        found = nodes.select("high", "low", F.col("node").alias("class_id"), "n")
    else:
        found = nodes.join(labels.withColumnRenamed("node", "at"), nodes["node"] == F.col("at"), "left").select("high", "low", F.coalesce("label", nodes["node"]).alias("class_id"), "n")
    found = stored(found, "classes")
    sizes = found.groupBy(F.col("class_id").alias("of")).agg(F.sum("n").alias("class_size"))
    found = found.join(sizes, F.col("class_id").eqNullSafe(F.col("of"))).select("high", "low", "class_id", "class_size")
    return rows.select("doc_id", "high", "low").join(found, ["high", "low"]).select("doc_id", "class_id", "class_size")


def _with_vectors(pairs: DataFrame, vectors: DataFrame) -> DataFrame:
    left = vectors.select(F.col("node").alias("a"), F.col("vector").alias("of_a"))
    right = vectors.select(F.col("node").alias("b"), F.col("vector").alias("of_b"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "of_a", "of_b")


def _near(least: float):
    """At least ``least`` alike: common >= least * (n_a + n_b - common)."""
    return F.col("common") >= least * (F.col("n_a") + F.col("n_b") - F.col("common")) - 1e-9


def _joined(docs: DataFrame, members: DataFrame, least: float) -> DataFrame | None:
    """Components of verified links between the members of shared buckets (``band, hash, node, n``); None if there are no links."""
    if members.isEmpty():
        return None
    popular = members.groupBy("node").agg(F.sum("n").alias("score"))
    text = id_and_text(docs)
    # one plan at every size: the texts are dealt by id, however few are wanted
    wanted = text.join(popular.select("node").hint("merge"), text["doc_id"] == popular["node"], "left_semi")
    vectors = stored(over_slices(wanted, _vectors, "node long, vector binary"), "vectors")
    ranked = members.join(popular, "node").select("band", "hash", "node", "score")
    hubs = ranked.groupBy("band", "hash").agg(F.max(F.struct("score", (-F.col("node")).alias("minus"))).alias("top"))
    hubs = hubs.select("band", "hash", (-F.col("top.minus")).alias("b"))
    pairs = members.select("band", "hash", F.col("node").alias("a")).join(hubs, ["band", "hash"]).where("a <> b").select("a", "b").distinct()
    compared = stored(_with_vectors(pairs, vectors).mapInArrow(_compared(least), COMPARED), "compared")
    links = compared.where(_near(least)).select("a", "b")
    labels = None if links.isEmpty() else components(links)
    rest = stored(_rest(compared, labels, least), "rest")
    more = _with_vectors(rest, vectors).mapInArrow(_compared(least), COMPARED)
    more = stored(more.where(_near(least)).select("a", "b"), "more_links")
    if more.isEmpty():
        return labels
    return components(links.union(more))


def _rest(compared: DataFrame, labels: DataFrame | None, least: float) -> DataFrame:
    """``a, b``: pairs that may be near though one of them (``a``) isn't near their common hub, across components."""
    if labels is None:
        rows = compared.withColumns({"label": F.col("a"), "hub_label": F.col("b")})
    else:
        of_a, of_b = (labels.select(F.col("node").alias(f"node_{x}"), F.col("label").alias(f"label_{x}")) for x in "ab")
        rows = compared.join(of_a, F.col("a") == F.col("node_a"), "left").join(of_b, F.col("b") == F.col("node_b"), "left")
        rows = rows.withColumns({"label": F.coalesce("label_a", "a"), "hub_label": F.coalesce("label_b", "b")})
    away = F.col("label") != F.col("hub_label")
    # the largest size of x that shares nothing with f outside the hub
    reach = F.when(away, F.floor(F.col("common") * (1 + least) / least - F.col("n_a") + 1e-9).cast("long"))
    rows = rows.select("a", F.col("b").alias("hub"), "label", "n_a", "common", "own", "inner", away.alias("away"), reach.alias("reach"), _near(least).alias("near"))
    busy = rows.groupBy("hub").agg(F.count("*").alias("n"), F.count(F.when(F.col("near"), 1)).alias("n_near"), F.max("away").alias("any"), F.max("reach").alias("most"))
    busy = busy.select(F.col("hub").alias("of"), "n", "n_near", "any", "most")
    rows = rows.join(busy, F.col("hub") == F.col("of")).drop("of")
    # any hub that two members have in common settles their case: the one that is near to most does
    own_hubs = rows.groupBy(F.col("a").alias("of")).agg(F.collect_set(F.struct("n_near", "hub")).alias("hubs"))  # one hub a band at most
    rows = rows.where("n > 1 and any").join(own_hubs, F.col("a") == F.col("of")).drop("of")
    inner = F.when(F.col("away") | (F.col("n_a") <= F.col("most")), F.transform("inner", lambda t: F.struct(t.alias("token"), F.lit(True).alias("in_hub")))).otherwise(F.array())
    both = F.concat(F.transform("own", lambda t: F.struct(t.alias("token"), F.lit(False).alias("in_hub"))), inner)
    tokens = rows.select("hub", "a", "label", "n_a", "common", "away", "reach", "hubs", F.inline(both))
    # the common order within a hub: rare tokens first, so that what members don't share fills their prefixes
    meets = tokens.groupBy("hub", "token").agg(F.count("*").alias("df"), F.max("away").alias("any"), F.min("label").alias("low"), F.max("label").alias("high"))
    rank = F.row_number().over(W.partitionBy("hub", "a", "in_hub").orderBy("df", "token")) - 1
    tokens = stored(tokens.join(meets, ["hub", "token"]).withColumn("rank", rank).where("any and low < high").drop("df", "any", "low", "high"), "tokens")
    f = tokens.where("away").drop("away")
    x = tokens.select("hub", "token", *[F.col(c).alias(f"{c}_x") for c in ("a", "label", "n_a", "common", "rank", "hubs")])
    # shingles outside the hub that two near members must share
    need = F.ceil((F.col("n_a") + F.col("n_a_x")) * least / (1 + least) - 1e-9) - F.least("common", "common_x")
    within = [F.col(f"rank{i}") <= F.when(need > 0, F.col(f"n_a{i}") - F.col(f"common{i}") - need).otherwise(F.floor(F.col(f"n_a{i}") * (1 - least) + 1e-9)) for i in ("", "_x")]
    settled = F.array_max(F.array_intersect("hubs", "hubs_x"))["hub"] == F.col("hub")
    meet = f.join(x, ["hub", "token"]).where(F.col("label") != F.col("label_x")).where((F.col("in_hub") & (need <= 0) & (F.col("n_a_x") <= F.col("reach"))) | ~F.col("in_hub") & within[0] & within[1]).where(settled)
    return meet.select(F.least("a", "a_x").alias("a"), F.greatest("a", "a_x").alias("b")).distinct()


def without_near_duplicates(docs: DataFrame, least: float = LIKENESS) -> DataFrame:
    """The rows of ``docs`` whose doc_id is its class's, with their columns: one document of each class.

    Rows of equal doc_id stay together; a row without doc_id stays where all of its class lack one.
    """
    classes = near_duplicates(docs, least)
    kept = classes.where("class_id is null or doc_id = class_id").select(F.col("doc_id").alias("__kept")).distinct()
    return docs.join(kept, docs["doc_id"].cast("long").eqNullSafe(F.col("__kept")), "left_semi")
