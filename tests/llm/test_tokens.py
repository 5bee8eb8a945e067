import random
import subprocess
import sys
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from tokenizers import Tokenizer

from coreshell.llm import bpe_counts, repair_store

from .conftest import ODD, documents

PIECES = ["a", "B", " ", "\n", ".", "é", "  ", "　", "\t", "1", "'s", "<|endoftext|>", "word", "\x1c", "\xa0", "Σ", "İ", "́", "ing"]


def odd_texts(n=400):
    r = random.Random(1)
    return [t or "" for _, t, _ in ODD] + ["".join(r.choice(PIECES) for _ in range(r.randint(0, 14))) for _ in range(n)]


def test_counts_equal_the_library():
    path = public_tokenizers.path("word_bpe_49k.json")
    library, own = Tokenizer.from_file(path), bpe_counts.MergeCounter(path)
    for t in odd_texts():
        assert own.count(t) == len(library.encode(t, add_special_tokens=False).ids), t


def test_count_rows(spark, odd, empty):
    path = public_tokenizers.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    found = sorted((r.doc_id if r.doc_id is not None else -1, r.n_bytes, r.n_tokens, r.over_limit) for r in bpe_counts.count_tokens(odd, path).collect())
    want = []
    for i, t, _ in ODD:
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        want.append((-1 if i is None else i, len((t or "").encode()), n, n > 2048))
    assert found == sorted(want)
    assert bpe_counts.count_tokens(empty, path).count() == 0


@pytest.mark.parametrize("end", [None, 0])
@pytest.mark.parametrize("most", [7, 1 << 20])
def test_encoder_equals_the_library(end, most):
    encoder = repair_store.Encoder(public_tokenizers.path("byte_bpe_50k.json"))
    texts = odd_texts()
    want = [encoder.tokenizer.encode(t, add_special_tokens=False).ids + ([] if end is None else [end]) for t in texts]
    for _ in range(2):  # the second time from memory
        got = {}
        for a, b, ids, lens in encoder.encode(pa.array(texts), end, most):
            cuts = np.r_[0, np.cumsum(lens)]
            got |= {i: ids[cuts[i - a] : cuts[i - a + 1]].tolist() for i in range(a, b)}
        assert [got[i] for i in range(len(texts))] == want


@pytest.mark.parametrize("bits", [0, 3])
def test_words_of_one_hash_keep_their_ids(monkeypatch, bits):
    """Known words are found by hash in an array that grows with them; words that share one must not get each other's ids."""
    full = repair_store.hashes
    monkeypatch.setattr(repair_store, "hashes", lambda words: full(words) & np.uint64((1 << bits) - 1))
    encoder = repair_store.Encoder(public_tokenizers.path("byte_bpe_50k.json"))
    texts = ["one two\nthree four,\nfive! one", "two three\nthree \u00e9t\u00e9 four, six", "\nseven one two"]
    want = [encoder.tokenizer.encode(t, add_special_tokens=False).ids for t in texts]
    for _ in range(2):
        assert [ids.tolist() for _, _, ids, _ in encoder.encode(pa.array(texts), None, 1)] == want


def pair_counts(symbols, barrier=0):
    """Occurrences of each pair, those that overlap another of the same pair left out."""
    out, last = Counter(), {}
    for i, pair in enumerate(zip(symbols, symbols[1:])):
        if barrier not in pair and last.get(pair) != i - 1:
            out[pair] += 1
            last[pair] = i
    return out


def one_by_one(ids, first_rule):
    """The sequential method: the most frequent pair, over and over; (symbols, rules)."""
    symbols, rules = list(ids), []
    while (counts := pair_counts(symbols)) and max(counts.values()) >= 2:
        pair = max(counts, key=lambda p: (counts[p], p))
        out, i = [], 0
        while i < len(symbols):
            hit = tuple(symbols[i : i + 2]) == pair
            out.append(first_rule + len(rules) if hit else symbols[i])
            i += 1 + hit
        symbols, rules = out, [*rules, pair]
    return symbols, rules


def test_grammar():
    r = np.random.default_rng(0)
    for n in (0, 1, 2, 3, 50, 5000):
        for top in (2, 5, 30):
            ids = r.integers(0, top, n).astype(np.uint32)
            symbols, rules = repair_store.compress(ids, 100, barrier=0)
            lens = repair_store.lengths(rules, 100)
            assert (repair_store.spelled(symbols, rules, lens, 100) == ids).all()
            assert not (rules == 0).any()  # nothing crosses the end of a document
            assert max(pair_counts(symbols.tolist()).values(), default=0) < 2
            assert len(set(map(tuple, rules.tolist()))) == len(rules)
            used = Counter(np.concatenate([symbols, rules.ravel()]).tolist())
            assert all(used[100 + i] >= 1 for i in range(len(rules)))
            counts = pair_counts(ids.tolist())
            most = [p for p in counts if counts[p] == max(counts.values()) >= 2]
            assert not most or {*map(tuple, rules.tolist())} & {*most}
    runs = np.full(1000, 7, np.uint32)
    symbols, rules = repair_store.compress(runs, 100)
    assert len(symbols) + len(rules) < 25 and (repair_store.spelled(symbols, rules, repair_store.lengths(rules, 100), 100) == runs).all()


def test_grammar_is_as_small_as_one_pair_at_a_time():
    r = random.Random(4)
    words = [[r.randint(1, 60) for _ in range(r.randint(2, 7))] for _ in range(40)]
    for seed in range(6):
        r = random.Random(seed)
        ids = [x for _ in range(300) for x in [*r.choice(words), *([0] if r.random() < 0.05 else [])]]
        symbols, rules = repair_store.compress(np.array(ids, np.uint32), 100)
        want, made = one_by_one(ids, 100)
        assert len(symbols) + 2 * len(rules) <= 1.1 * (len(want) + 2 * len(made))


def test_counting_without_room_for_places():
    left, right = np.array([5, 6, 5, 9], np.int32), np.array([6, 5, 6, 9], np.int32)
    for bits in (4, 31):
        order, count, pairs = repair_store._counted(left, right, bits)
        assert sorted(order.tolist()) == [0, 2] and count.tolist() == [2] and pairs.tolist() == [[5, 6]]


def test_a_slice_follows_covering_rules_only():
    ids = np.random.default_rng(1).integers(1, 9, 20000).astype(np.uint32)
    symbols, rules = repair_store.compress(ids, 100)
    lens = repair_store.lengths(rules, 100)
    for a, b in ((0, 1), (777, 790), (19990, 20000), (5, 5), (0, 20000)):
        seen = []
        assert (repair_store.spelled(symbols, rules, lens, 100, a, b, seen) == ids[a:b]).all()
        # a rule that covers an end is followed once a level; all others lie inside
        assert sum(map(len, seen)) <= 2 * (b - a) + 2 * 40
    assert len(rules) > 500


def test_memory_of_texts_with_runs_of_blanks():
    """Such texts take the library's objects in small batches: 24 MB of them may not take 300 MB."""
    code = """
import resource, sys
import numpy as np, pyarrow as pa, public_tokenizers
from coreshell.llm import repair_store
r = np.random.default_rng(0)
words = ["".join(x) for x in r.choice(list("abcdefghij"), (50000, 7))]
texts = [("  ".join(r.choice(words, 3000))) for _ in range(900)]
e = repair_store.Encoder(public_tokenizers.path("byte_bpe_50k.json"))
list(e.encode(pa.array(texts[:1]), 0))
before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
batch = pa.record_batch([pa.array(range(900)), pa.array(texts)], names=["a", "b"])
for part in repair_store.slices([batch], most=repair_store.ENCODED_BYTES):
    for _ in e.encode(part.column(1), 0):
        pass
print((resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before) // 1024)
"""
    out = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, check=True)
    assert int(out.stdout) < 300


def test_files(spark, odd, empty):
    path = public_tokenizers.path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    table, first_rule = repair_store.write_ids(odd, path, shard_ids=500)
    rows = repair_store.read_documents(table, first_rule).collect()
    order = sorted(ODD, key=lambda r: (r[0] is not None, r[0] or 0))
    start, want = 0, []
    for i, t, _ in order:
        ids = library.encode(t or "", add_special_tokens=False).ids + [0]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    assert sorted(((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in rows), key=lambda r: r[1]) == want
    row = max((r.asDict() for r in table.collect()), key=lambda r: r["n_ids"])
    whole = repair_store.read_slice(row, first_rule, 0, row["n_ids"])
    for a, b in ((0, 1), (3, 40), (row["n_ids"] - 2, row["n_ids"]), (5, 5)):
        assert (repair_store.read_slice(row, first_rule, a, b) == whole[a:b]).all()
    table, first_rule = repair_store.write_ids(empty, path)
    assert repair_store.read_documents(table, first_rule).count() == 0


def test_whole_fixture_is_documents(spark):
    assert documents(spark, ODD).count() == len(ODD)


def test_the_grammar_finds_places_by_sorting_not_by_a_table(monkeypatch):
    ids = np.random.default_rng(3).integers(1, 60, 4000)
    want = repair_store.compress(ids, 100)
    monkeypatch.setattr(np, "unique", None)
    symbols, rules = repair_store.compress(ids, 100)
    assert (symbols == want[0]).all() and (rules == want[1]).all()
    assert (repair_store.spelled(symbols, rules, repair_store.lengths(rules, 100), 100) == ids).all()
