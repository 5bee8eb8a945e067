import math
import random
import tracemalloc
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

import corpus_pipeline
from coreshell.llm import budget_mix, dart_minhash, decontaminate, lm_difference, toxicity

from .conftest import ODD, SCHEMA, documents, prose

# --- near duplicates -----------------------------------------------------------


def shingle_bag(text):
    words = text.lower().split()
    return Counter(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))) if words else Counter()


def jaccard(a, b):
    both = sum((a & b).values())
    return both / (sum(a.values()) + sum(b.values()) - both)


def brute_classes(rows):
    bags = {i: (t or "").lower().split() for i, t in rows}
    of = {i: i for i in bags}

    def root(i):
        while of[i] != i:
            i = of[i]
        return i

    ids = sorted(bags)
    for x, i in enumerate(ids):
        for j in ids[x + 1 :]:
            same = bags[i] == bags[j]
            if same or bags[i] and bags[j] and jaccard(shingle_bag(" ".join(bags[i])), shingle_bag(" ".join(bags[j]))) >= 0.8:
                a, b = sorted((root(i), root(j)))
                of[b] = a
    return {i: root(i) for i in ids}


def edited(text, seed, n, drop=0):
    r = random.Random(seed)
    words = text.split()
    for _ in range(n):
        words[r.randrange(len(words))] = f"new{r.randrange(10**6)}"
    return " ".join(words[: len(words) - drop])


def families():
    rows = [(i, prose(1000 + i, 60)) for i in range(30)]
    star, chain = prose(1, 200), prose(2, 200)
    rows += [(100 + i, edited(star, i, 3 + i % 6)) for i in range(40)] + [(95, star)]
    for i in range(8):
        rows.append((200 + i, chain))
        chain = edited(chain, 50 + i, 2)
    long = prose(3, 220)
    rows += [(300 + i, edited(long, i, 0, drop=12 * i)) for i in range(8)]  # ever shorter
    other = star.split()[:100] + prose(4, 100).split()  # half of a family's text
    rows += [(400 + i, edited(" ".join(other), i, 2 + i % 4)) for i in range(12)]
    return rows + [(500, rows[0][1].upper()), (501, "  " + rows[0][1].replace(" ", "\n")), (502, "short text"), (503, "Short  text")]


def test_near_duplicate_classes_equal_brute_force(spark):
    rows = families()
    found = {r.doc_id: r.class_id for r in dart_minhash.near_duplicates(documents(spark, [(i, t, "s") for i, t in rows])).collect()}
    assert found == brute_classes(rows)


def test_near_duplicate_edges(spark, odd, empty):
    rows = dart_minhash.near_duplicates(odd).collect()
    assert len(rows) == len(ODD)
    by = {r.doc_id: (r.class_id, r.class_size) for r in rows}
    assert by[0] == by[1] == by[2] == (0, 3) and by[5] == (5, 2) and by[None] == (None, 1)
    assert dart_minhash.near_duplicates(empty).count() == 0
    kept = dart_minhash.without_near_duplicates(odd)
    assert kept.columns == odd.columns and sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == [0, 3, 4, 5, 5, 7, 8]


def test_darts_agree_as_often_as_documents_are_alike():
    a = prose(1, 400)
    texts = [a, edited(a, 1, 10), edited(a, 2, 40), a + " " + a, prose(9, 3)]
    where, words = dart_minhash.word_hashes(pa.array(texts))
    darts, real = dart_minhash.signatures(dart_minhash.shingles(where, words, len(texts)), len(texts), coordinates=2000)
    assert real.all()
    for i, j in ((0, 1), (0, 2), (1, 2), (0, 3), (0, 4)):
        assert abs((darts[i] == darts[j]).mean() - jaccard(shingle_bag(texts[i]), shingle_bag(texts[j]))) < 0.05


# --- leaks ----------------------------------------------------------------------


def naive(pattern, text):
    before = list(range(len(pattern) + 1))
    best = before[-1]
    for c in text:
        now = [0]
        for i, p in enumerate(pattern, 1):
            now.append(min(before[i] + 1, now[-1] + 1, before[i - 1] + (p != c)))
        before = now
        best = min(best, now[-1])
    return best


def typo(text, n, r):
    for _ in range(n):
        i = r.randrange(len(text))
        text = text[:i] + r.choice(["", "q", text[i] + "q"]) + text[i + 1 :]
    return text


def test_leaks_equal_brute_force(spark, empty):
    r = random.Random(5)
    items = [(i, prose(2000 + i, 25)) for i in range(6)] + [(90, ""), (91, None), (92, "tiny")]
    rows = []
    for i in range(60):
        item = items[i % 6][1]
        middle = typo(item, r.randrange(0, 14), r).upper().replace(" ", "\n  ") if i % 3 else ""
        rows.append((i, prose(3000 + i, 30) + " " + middle + " " + prose(4000 + i, 30), "s"))
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    hits = decontaminate.leaks(documents(spark, rows), benchmark).collect()
    want = set()
    for i, t, _ in rows:
        for k, p in items[:6]:
            p = decontaminate.folded(p)
            if naive(p, decontaminate.folded(t)) <= decontaminate.budget(len(p), decontaminate.ERROR_RATE):
                want.add((i, k))
    assert {(h.doc_id, h.item_id) for h in hits} == want and len(want) > 15
    text = {i: t for i, t, _ in rows}
    for h in hits:
        p = decontaminate.folded(dict(items)[h.item_id])
        assert naive(p, decontaminate.folded(text[h.doc_id][h.start : h.end])) == h.distance
    docs = documents(spark, rows)
    assert {x.doc_id for x in decontaminate.clean(docs, benchmark).collect()} == {i for i, *_ in rows} - {i for i, _ in want}
    assert decontaminate.leaks(empty, benchmark).count() == 0
    assert decontaminate.leaks(docs, benchmark.limit(0)).count() == 0
    assert len(list(decontaminate.item_blocks(benchmark, 100))) > 3


def test_short_items_match_as_whole_words(spark):
    benchmark = spark.createDataFrame([(1, "Ab  cd"), (2, "é"), (3, "  ")], "item_id long, text string")
    rows = [(1, "x ab cd", "s"), (2, "xab cd y ab cdx", "s"), (3, "AB\nCD, no; É ab cd ab cd", "s"), (4, "ab c d", "s")]
    found = sorted((r.doc_id, r.item_id, r.start, r.end) for r in decontaminate.leaks(documents(spark, rows), benchmark).collect())
    assert found == [(1, 1, 2, 7), (3, 1, 13, 18), (3, 1, 19, 24), (3, 2, 11, 12)]


def test_rows_are_judged_by_their_own_text(spark):
    item = prose(2000, 25)
    benchmark = spark.createDataFrame([(1, item), (2, prose(2001, 25))], "item_id long, text string")
    rows = [(None, item, "s"), (None, "clean without id", "s"), (7, "x " + item, "s"), (7, "clean of the same id", "s"), (8, None, "s")]
    docs = documents(spark, rows)
    left = decontaminate.clean(docs, benchmark)
    assert left.columns == docs.columns and {r.text for r in left.collect()} == {"clean without id", "clean of the same id", None}
    assert decontaminate.clean(docs, benchmark.limit(0)).count() == len(rows)


# --- mixing ----------------------------------------------------------------------


def test_targets():
    t = budget_mix.targets({"b": 100, "a": 1000, None: 10, "c": 1000})
    assert t[None] == 20 and t["b"] == 200  # capped at twice their size
    assert abs(sum(t.values()) - 1.5 * 2110) < 1e-6 and t["a"] / t["c"] == 5 or t["a"] == 2000
    assert budget_mix.targets({}) == {} and budget_mix.targets({"a": 0}) == {"a": 0.0}


def test_fit_is_optimal():
    r = random.Random(1)
    for _ in range(400):
        lengths = r.sample(range(0, 40), r.randint(1, 6))
        counts = [r.randint(0, 6) for _ in lengths]
        total = sum(a * b for a, b in zip(lengths, counts))
        budget = r.randint(0, total + 3)
        k = budget_mix.fit(lengths, counts, budget)
        assert all(0 <= x <= n for x, n in zip(k, counts))
        found = sum(a * x for a, x in zip(lengths, k))
        assert found <= budget
        sums = {0}
        for length, n in zip(lengths, counts):
            sums = {x + length * i for x in sums for i in range(n + 1)}
        if budget <= budget_mix.LEFT_LENGTHS * max(lengths):  # all of it is the programme's
            assert found == max(x for x in sums if x <= budget)


def test_fit_keeps_lengths_in_proportion():
    lengths, counts = list(range(1, 200)), [5000 // (i + 1) + 1 for i in range(199)]
    total = sum(a * b for a, b in zip(lengths, counts))
    k = budget_mix.fit(lengths, counts, total // 3)
    assert sum(a * x for a, x in zip(lengths, k)) == total // 3
    few, many = sum(a * x for a, x in zip(lengths[:100], k)), sum(a * x for a, x in zip(lengths[:100], counts))
    assert abs(few / many - 1 / 3) < 0.05
    # a budget that no sum can reach
    assert sum(6 * a * x for a, x in zip(lengths, budget_mix.fit([6 * a for a in lengths], counts, 2 * total + 5))) == (2 * total + 5) // 6 * 6


def test_mix(spark, odd, empty):
    r = random.Random(2)
    rows = [(i, " ".join(["w"] * (r.randint(0, 12) if i % 4 else 7)), ["a", "b", "c", None][min(3, r.randrange(10))]) for i in range(600)]
    docs = documents(spark, rows)
    found = budget_mix.mix(docs).collect()
    assert len(found) == 600
    size = {i: len(t.split()) for i, t, _ in rows}
    by = Counter()
    for i, _, s in rows:
        by[s] += size[i]
    goal, taken = budget_mix.targets(dict(by)), Counter()
    source = {i: s for i, _, s in rows}
    for x in found:
        assert (x.size, x.source_size, x.target) == (size[x.doc_id], by[source[x.doc_id]], goal[source[x.doc_id]])
        assert x.taken in (0, x.size, 2 * x.size)
        taken[source[x.doc_id]] += x.taken
    assert all(abs(taken[s] - goal[s]) <= 1 for s in by)
    assert sorted(map(tuple, found)) == sorted(map(tuple, budget_mix.mix(docs.repartition(3)).collect()))
    copies = Counter(x.doc_id for x in budget_mix.mixed_documents(docs).collect())
    assert all(copies[x.doc_id] == x.taken // x.size for x in found if x.size)
    assert len(budget_mix.mix(odd).collect()) == len(ODD)
    assert budget_mix.mix(empty).count() == 0


def test_documents_of_size_zero_are_mixed_too(spark):
    rows = [(0, None, "a"), (1, " ", "a"), (2, "w w", "a")] + [(i, "w " * 9, "b") for i in range(10, 40)]
    copies = Counter(x.doc_id for x in budget_mix.mixed_documents(documents(spark, rows)).collect())
    assert copies[0] == copies[1] == copies[2] == 2  # a small source is taken twice


# --- toxicity ----------------------------------------------------------------------


def toxic_rows(n=900):
    r = random.Random(3)
    rows, labels = [], []
    for i in range(n):
        sentences = [prose(i * 50 + k, 8) for k in range(r.randint(1, 9))]
        bad = i % 5 == 0
        if bad:
            k = r.randrange(len(sentences))
            sentences[k] += " vilest" + r.choice(["er", "ing", "on", "ou", "an"]) + " things"
        rows.append((i, ". ".join(sentences) + ".", "s"))
        labels.append((i, int(bad), 9))
    return rows, labels


def test_toxicity(spark, odd, empty):
    rows, labels = toxic_rows()
    docs, marked = documents(spark, rows), spark.createDataFrame(labels, "doc_id long, toxic int, source int")
    model = toxicity.train(docs, marked)
    found = {r.doc_id: r for r in toxicity.score(docs, model).collect()}
    assert {i: r.held_out for i, r in found.items()} == {i: zlib.crc32(str(i).encode()) % 3 == 1 for i, *_ in rows}
    for i, bad, _ in labels:
        r = found[i]
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) == bad, i
        if bad:
            assert "vilest" in rows[i][1].split(". ")[r.top_sentence]
    # labels of held-out rows make no difference
    flipped = spark.createDataFrame([(i, 1 - y if zlib.crc32(str(i).encode()) % 3 == 1 else y, 0) for i, y, _ in labels], "doc_id long, toxic int, source int")
    assert toxicity.train(docs, flipped) == model
    spans = toxicity.offending_sentences(docs, model).collect()
    assert spans and all("vilest" in s.text for s in spans)
    assert {r.doc_id for r in toxicity.without_toxic(docs, model).collect()} == {i for i, bad, _ in labels if not bad}
    rows = toxicity.score(odd, model).collect()
    assert len(rows) == len(ODD) and all(r.score == 0 and r.top_sentence is None for r in rows if r.doc_id in (0, 1, 2))
    assert toxicity.score(empty, model).count() == 0
    untrained = toxicity.train(docs, marked.limit(0))
    assert all(r.predicted == 0 for r in toxicity.score(odd, untrained).collect())


def brute_fit(texts, labels, steps, l2):
    """Noisy-or over sentences by a plain gradient in dictionaries; every word and beginning of a word is a feature."""
    bags = [[{f for w in map(toxicity.fold, x.split()) if w for f in toxicity.features(w)} for x in t.split(".") if x.strip()] for t in texts]
    theta, first, second = Counter(), Counter(), Counter()
    theta["bias"] = math.log(np.mean(labels) / max(1.0, sum(map(len, bags)) / len(texts)))
    keys = {f for b in bags for s in b for f in s} | {"bias"}
    for t in range(1, steps + 1):
        grad = Counter({k: l2 * theta[k] for k in keys if k != "bias"})
        for bag, y in zip(bags, labels):
            p = [1 / (1 + math.exp(-sum(theta[f] for f in s) - theta["bias"])) for s in bag]
            none = math.prod(1 - x for x in p)
            pull = (-none / max(1 - none, 1e-9) if y else 1.0) / len(texts)
            for s, x in zip(bag, p):
                for f in s | {"bias"}:
                    grad[f] += pull * x
        for k in keys:
            first[k] = 0.9 * first[k] + 0.1 * grad[k]
            second[k] = 0.999 * second[k] + 0.001 * grad[k] ** 2
            theta[k] -= 0.1 * (first[k] / (1 - 0.9**t)) / (math.sqrt(second[k] / (1 - 0.999**t)) + 1e-9)
    return theta


def test_the_fit_is_the_noisy_or_gradient():
    r = random.Random(5)
    texts, labels = [], []
    for i in range(40):
        bad = i % 3 == 0
        sentences = [" ".join(r.choice(["ab", "cd", "ef", "gh"]) for _ in range(4)) for _ in range(r.randint(1, 4))]
        if bad:
            sentences[r.randrange(len(sentences))] += " vi"
        texts.append(". ".join(sentences))
        labels.append(int(bad))
    s = toxicity.Settings(least_documents=0, least_z=-1.0, steps=25)
    model = toxicity.fit(texts, np.array(labels), np.ones(40), s)
    want = brute_fit(texts, labels, 25, s.l2)
    assert model.bias == pytest.approx(want["bias"], abs=1e-6)
    assert set(model.weights) - {""} == {"ab", "cd", "ef", "gh", "vi"} and all(w == pytest.approx(want[f], abs=1e-6) for f, w in model.weights.items())
    # a document's score is the noisy-or of its sentences
    doc, x = toxicity._sentence_scores(pa.array(["ab vi. cd cd ef", "gh"]), model)
    assert doc.tolist() == [0, 0, 1] and x == pytest.approx([sum(model.weights[w] for w in bag) + model.bias for bag in (("ab", "vi"), ("cd", "ef"), ("gh",))])


# --- language models ------------------------------------------------------------------


def brute_losses(rows, good, share, prior):
    texts = [(i, (t or "").lower().split()) for i, t, _ in rows]
    total = Counter(w for _, t in texts for w in t)
    vocab = {w for w, n in total.items() if n >= share * sum(total.values())}
    code = lambda t: ["<s>"] + [w if w in vocab else None for w in t]
    pairs = {"b": Counter(), "t": Counter()}
    for i, t in texts:
        for kind in ["b"] + ["t"] * (i in good):
            pairs[kind].update(zip(code(t), code(t)[1:]))
    out = {}
    for kind, count in pairs.items():
        before, word = Counter(), Counter()
        for (v, w), n in count.items():
            before[v] += n
            word[w] += n
        n, size = sum(word.values()), len(vocab) + 2
        out[kind] = lambda v, w, c=count, b=before, u=word, n=n, size=size: -math.log((c[v, w] + prior * (u[w] + 1) / (n + size)) / (b[v] + prior))
    return [(i, len(t), *([sum(out[k](v, w) for v, w in zip(code(t), code(t)[1:])) / len(t) for k in "tb"] if t else [None, None])) for i, t in texts]


def test_losses_equal_brute_force(spark, odd, empty):
    rows = [(i, prose(i % 7, 30) + " " + prose(i, 10), "s") for i in range(40)] + [(90, "", "s"), (91, None, "s"), (5, "a b a b", "s")]
    good = {i for i in range(40) if i % 3 == 0}
    ids = spark.createDataFrame([(i, 1) for i in good] + [(None, 1)], "doc_id long, quality int")
    found = lm_difference.score(documents(spark, rows), ids, least_share=0.005, prior=5.0).collect()
    key = lambda r: (r[0], r[1])
    for got, want in zip(sorted(map(tuple, found), key=key), sorted(brute_losses(rows, good, 0.005, 5.0), key=key), strict=True):
        assert got[:2] == want[:2]
        if want[2] is None:
            assert got[2] is None and got[4] is None
        else:
            assert got[2] == pytest.approx(want[2], abs=1e-5) and got[3] == pytest.approx(want[3], abs=1e-5) and got[4] == pytest.approx(want[2] - want[3], abs=1e-5)
    assert len(lm_difference.score(odd, ids).collect()) == len(ODD)
    assert lm_difference.score(empty, ids).count() == 0


def test_the_vocabulary_grows_with_the_corpus(spark):
    # every word twice, in each of 60,000: none has 2e-5 of all tokens
    rows = [(i, " ".join(f"w{k}" for k in range(600 * (i % 100), 600 * (i % 100) + 600)), "s") for i in range(200)] + [(900, "once only", "s")]
    docs = documents(spark, rows)
    words, n = lm_difference.vocabulary(lm_difference.chunked(docs))
    ids = np.concatenate([lm_difference.unpacked(r.blob, 2)[0] for r in words.collect()])
    assert n == 60000 == len(set(ids.tolist()) - {0})
    target = spark.createDataFrame([(5,)], "doc_id long")
    found = {r.doc_id: r for r in lm_difference.score(docs, target).collect()}
    assert found[5].difference < found[6].difference and found[105].difference == pytest.approx(found[5].difference)


def test_chunks_share_their_counts(spark, monkeypatch):
    rows = [(i, prose(i % 7, 30) + " " + prose(i, 10), "s") for i in range(40)]
    ids = spark.createDataFrame([(i,) for i in range(0, 40, 3)], "doc_id long")
    monkeypatch.setattr(lm_difference, "CHUNK_WORDS", 1)
    monkeypatch.setattr(lm_difference, "BUCKET_KEYS", 100)
    found = {r.doc_id: r for r in lm_difference.score(documents(spark, rows).repartition(9), ids, prior=5.0).collect()}
    n = sum(len(t.split()) for _, t, _ in rows)
    for i, k, t, b in brute_losses(rows, set(range(0, 40, 3)), 2 / n, 5.0):
        assert (found[i].n_words, found[i].target_loss, found[i].background_loss) == (k, pytest.approx(t, abs=1e-9), pytest.approx(b, abs=1e-9))


# --- the pipeline -----------------------------------------------------------------------


def test_pipeline(spark, tmp_path):
    rows, labels = toxic_rows(300)
    clean = [i for i, bad, _ in labels if not bad]
    rows += [(1000 + i, rows[i][1] + " tail", "s") for i in clean[:9]]  # near copies of some
    leak = prose(77, 30)
    rows += [(2000 + i, prose(5000 + i, 20) + " " + leak + " " + prose(6000 + i, 20), "t") for i in range(5)]
    documents(spark, rows).write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, toxic int, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame([(1, leak)], "item_id long, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    d = str(tmp_path)
    docs = spark.read.parquet(f"{d}/documents.parquet")
    steps = dict(corpus_pipeline.STAGES)
    assert list(steps) == ["toxicity", "near_duplicates", "decontamination", "mixing", "token_ids"]
    one = steps["toxicity"](spark, docs, d)
    assert one.schema == docs.schema
    toxic = {i for i, bad, _ in labels if bad}
    assert {r.doc_id for r in one.collect()} == {i for i, *_ in rows} - toxic
    two = steps["near_duplicates"](spark, one, d)
    left = {r.doc_id for r in two.collect()}
    assert left == {i for i, c in brute_classes([(i, t) for i, t, _ in rows if i not in toxic]).items() if i == c}
    three = steps["decontamination"](spark, two, d)
    assert {r.doc_id for r in three.collect()} == {i for i in left if i < 2000}
    four = steps["mixing"](spark, three, d)
    assert four.columns == docs.columns
    last = corpus_pipeline.run(spark, d)
    assert sorted(r.doc_id for r in last.collect()) == sorted(r.doc_id for r in four.collect())
    assert np.isclose(sum(len(r.text.split()) for r in four.collect()), sum(r.target for r in budget_mix.mix(three).select("target").distinct().collect()), atol=3)


def test_pipeline_of_odd_documents(spark, tmp_path):
    """Nulls in any column, empty and long texts, repeated rows, columns with clashing names; and no documents at all."""
    labels = spark.createDataFrame([(3, 1, 0), (7, 0, None), (None, 1, 1), (8, None, 1)], "doc_id long, toxic int, quality int")
    benchmark = spark.createDataFrame([(1, "no id here at all, really"), (2, None), (None, ""), (3, "x" * 40)], "item_id long, text string")
    for name, rows in (("odd", ODD), ("none", [])):
        d = str(tmp_path / name)
        documents(spark, rows).write.parquet(f"{d}/documents.parquet")
        labels.write.parquet(f"{d}/labels.parquet")
        benchmark.write.parquet(f"{d}/benchmark.parquet")
        docs = spark.read.parquet(f"{d}/documents.parquet")
        for stage, step in corpus_pipeline.STAGES[:-1]:
            after = corpus_pipeline.stored(step(spark, docs, d), stage)
            assert after.columns == docs.columns, stage
            docs = after
        kept = Counter(r.doc_id for r in docs.collect())
        found = Counter(r.doc_id for r in corpus_pipeline.run(spark, d).collect())
        assert found == kept and None not in kept and 7 not in kept  # the leaks are gone
        assert set(kept) <= {0, 3, 4, 5, 8} and (not rows or kept)


def test_schema_has_clashing_names():
    assert {"n", "label", "hub", "row", "part", "size", "copy"} <= {c.split()[0] for c in SCHEMA.split(", ")}


def test_the_fit_counts_features_in_blocks():
    """Documents have several features a word: counted all at once, the fit took 213 MB here, in blocks 91."""
    draw = np.random.default_rng(3)
    words = ["".join(x) for x in draw.choice(list("abcdefghijklmnop"), (3000, 10))]
    texts = [" ".join(draw.choice(words, 300)) for _ in range(2500)]
    labels = np.arange(len(texts)) % 2
    tracemalloc.start()
    try:
        toxicity.fit(texts, labels, np.ones(len(texts)), toxicity.Settings(steps=1))
        assert tracemalloc.get_traced_memory()[1] < 150 << 20
    finally:
        tracemalloc.stop()
