"""Token ids in a grammar-compressed binary format, and its readers.

A shard is one row of a Parquet table: the ids of consecutive documents, in which pairs of neighbouring symbols were
replaced by new symbols, the most frequent first, until no pair occurs twice. It holds the rules, the expansion length
of each rule, the remaining symbols and the documents' ids and lengths; a cumulative sum of expansion lengths leads
straight to any position, and from there only rules that cover it are followed.

Fields (little-endian): ``doc_ids`` int64, ``doc_lens`` uint32, ``rules`` uint32 pairs (left, right), ``rule_lens``
uint32, ``low`` and ``high`` uint16 (symbol = high * 65536 + low), ``no_id`` bytes (1: the document has no id).
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.llm.shared import id_and_text, memory, plain, returned, shared_dir, slices, stored, strings

SHARD_IDS = 1 << 20
#: Bytes of text whose distinct words are looked up together.
ENCODED_BYTES = 10 << 20
#: Bytes of text handed to the tokenizers library at once; its results take some hundred bytes an id until they are arrays.
BATCH_BYTES = 1 << 18
#: Bytes of words in one of those texts, unless a word is longer.
ROW_BYTES = 1 << 12
#: Bytes of words and their ids that a worker remembers.
REMEMBERED_BYTES = 96 << 20
SCHEMA = "part int, seq int, n_docs long, n_ids long, ids_before long, doc_ids binary, no_id binary, doc_lens binary, rules binary, rule_lens binary, low binary, high binary"
#: Two white-space characters side by side (Unicode's property White_Space).
SPACES = r"[\s\x0b\x{85}\p{Z}][\s\x0b\x{85}\p{Z}]"
#: A space that stands alone, where any text may be cut.
LONE_SPACE = re.compile(r"(?<=\S) (?=\S)")


# --- grammar ---------------------------------------------------------------


def compress(ids: np.ndarray, first_rule: int, barrier: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(symbols, rules): pairs of neighbours become new symbols until no pair occurs twice without overlap.

    Symbols form a linked list. A step counts all pairs exactly and replaces every pair wherever it is more frequent than
    the pairs it overlaps there (ties by a hash of its rank), which is what taking one pair after the other by falling
    count comes to wherever pairs don't touch. The most frequent pair of all is always replaced, so the steps end. A step
    counts places whose pair is new, or occurred twice or more at the last count; when they give out, all places are
    counted again, as a rule used anew may have met a pair that stood alone before. Of the overlapping occurrences in a run of one symbol every other one counts. A pair with ``barrier``
    (the end of a document) is never replaced, so no rule crosses documents. Rules use symbols of earlier rules only.
    """
    n = len(ids)
    sym = np.full(n + 2, barrier, np.int32)
    sym[1 : n + 1] = ids
    following, preceding = np.arange(1, n + 3, dtype=np.int32), np.arange(-1, n + 1, dtype=np.int32)
    following[n + 1], preceding[0] = n + 1, 0
    mark = np.zeros(n + 2, bool)
    live, all_places = np.flatnonzero(sym[1:-1] != barrier).astype(np.int32) + 1, True
    rules, made = [], 0
    known, known_as = np.array([1 << 62]), np.zeros(1, np.int32)
    while len(live) or not all_places:
        follow = following[live]
        left, right = sym[live], sym[follow]
        keep = right != barrier
        skipped = _overlapping(live, follow, left, right)
        keep[skipped] = False
        skipped = live[skipped]
        keep = np.flatnonzero(keep)
        if len(keep) < len(live):
            live, follow, left, right = live[keep], follow[keep], left[keep], right[keep]
        order, count, pairs = _counted(left, right, (first_rule + made).bit_length())
        if not len(count):
            if all_places:
                break
            live, all_places = np.flatnonzero((sym[1:-1] >= 0) & (sym[1:-1] != barrier)).astype(np.int32) + 1, True
            continue
        codes = np.full(len(live), -1, np.int32)
        codes[order] = np.repeat(np.arange(len(count), dtype=np.int32), count)
        rank = np.append(count << 32 | np.arange(1, len(count) + 1) * 0x9E3779B1 & 0xFFFFFFFF, 0)[codes]  # 0 for a pair that stands alone
        meets, rises = follow[:-1] == live[1:], rank[1:] > rank[:-1]
        best = codes >= 0
        best[1:] &= ~meets | rises
        best[:-1] &= ~(meets & rises)
        best = np.flatnonzero(best)
        at, which = live[best], codes[best]
        good = np.bincount(which, minlength=len(count)) >= 2
        if not (twice := good[which]).all():
            at, which = at[twice], which[twice]
        chosen = np.flatnonzero(good)
        # a pair may have a rule already, made where it was the most frequent
        key = pairs[chosen, 0] << 32 | pairs[chosen, 1]
        place = np.searchsorted(known, key)
        old = known[np.minimum(place, len(known) - 1)] == key
        new = chosen[~old]
        number = np.zeros(len(count), np.int32)
        number[chosen[old]], number[new] = known_as[place[old]], first_rule + made + np.arange(len(new))
        known, known_as = np.insert(known, place[~old], key[~old]), np.insert(known_as, place[~old], number[new])
        rules.append(pairs[new])
        made += len(new)
        gone = following[at]
        after, before = following[gone], preceding[at]
        sym[at], sym[gone] = number[which], -1
        following[at], preceding[after] = after, at
        all_places = False
        live = live[codes >= 0]
        again = [live, skipped, before[sym[before] != barrier]]
        if 16 * len(live) > n:
            for some in again:
                mark[some] = True
            mark[gone] = False
            live = np.flatnonzero(mark).astype(np.int32)
            mark[live] = False
        else:
            live = np.concatenate(again)
            live = np.sort(live[sym[live] >= 0])  # sorting is faster than the table by which numpy finds distinct numbers
            live = live[np.r_[True, live[1:] != live[:-1]]] if len(live) else live
    out = sym[1 : n + 1]
    return out[out >= 0].astype(np.int64), (np.concatenate(rules) if rules else np.zeros((0, 2), np.int64))


def _overlapping(live: np.ndarray, follow: np.ndarray, left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Every second one of the places in ``live`` where pairs of one symbol overlap."""
    same = np.flatnonzero(left == right)
    if not len(same):
        return same
    begins = np.r_[True, (live[same][1:] != follow[same][:-1]) | (left[same][1:] != left[same][:-1])]
    index = np.arange(len(same))
    return same[((index - np.maximum.accumulate(np.where(begins, index, 0))) & 1) == 1]


def _counted(left: np.ndarray, right: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of the pairs that occur twice or more: (places, grouped by pair; occurrences; the pairs). Symbols have ``bits``."""
    places = len(left).bit_length()
    keys = left.astype(np.uint64) << np.uint64(bits) | right.astype(np.uint64)
    if 2 * bits + places <= 64:  # pair and place in one number, which sorts faster
        keys <<= np.uint64(places)
        keys |= np.arange(len(left), dtype=np.uint64)
        keys.sort()
        order = (keys & np.uint64((1 << places) - 1)).astype(np.int32)
        keys >>= np.uint64(places)
    else:
        order = np.argsort(keys, kind="stable")
        keys = keys[order]
    first = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, np.int64)
    count = np.diff(np.r_[first, len(keys)])
    twice = count >= 2
    inside = np.repeat(twice, count)
    first, count = first[twice], count[twice]
    pairs = np.stack([keys[first] >> np.uint64(bits), keys[first] & np.uint64((1 << bits) - 1)], 1).astype(np.int64)
    return order[inside], count, pairs


def gathered(pool: np.ndarray, begin: np.ndarray, size: np.ndarray, block: int = 1 << 16) -> np.ndarray:
    """The stretches of ``pool`` from ``begin`` of ``size`` laid end to end, in blocks that stay in the processor's cache."""
    ends = np.cumsum(size)
    out = np.empty(int(ends[-1]) if len(ends) else 0, pool.dtype)
    for i in range(0, len(size), block):
        n, e = size[i : i + block], ends[i : i + block]
        first = int(e[0] - n[0])
        at = np.repeat(begin[i : i + block].astype(np.int64) - e + n + first, n)
        at += np.arange(len(at))
        out[first : first + len(at)] = pool[at]
    return out


def lengths(rules: np.ndarray, first_rule: int) -> np.ndarray:
    """How many ids each rule stands for."""
    out, todo = np.zeros(len(rules), np.int64), np.arange(len(rules))
    while len(todo):
        sides = rules[todo]
        known = np.where(sides < first_rule, 1, out[np.maximum(sides - first_rule, 0)])
        done = (known > 0).all(1)
        out[todo[done]] = known[done].sum(1)
        todo = todo[~done]
    return out


def spelled(symbols: np.ndarray, rules: np.ndarray, rule_lens: np.ndarray, first_rule: int, start: int = 0, stop: int | None = None, visited: list | None = None) -> np.ndarray:
    """The ids ``start`` to ``stop`` (all) that ``symbols`` stand for; only rules that cover them are followed, and noted in ``visited``."""
    wide = np.concatenate([np.ones(first_rule, np.int64), rule_lens])
    ends = np.cumsum(wide[symbols])
    total = int(ends[-1]) if len(ends) else 0
    stop = total if stop is None else min(stop, total)
    a, b = np.searchsorted(ends, start, "right"), np.searchsorted(ends, stop, "left") + 1
    symbols = symbols[a:b]
    begin = ends[a:b] - wide[symbols]
    out = np.empty(max(0, stop - start), np.uint32)
    whole = start <= 0 and stop == total
    while len(symbols):
        if not whole:
            inside = (begin < stop) & (begin + wide[symbols] > start)
            symbols, begin = symbols[inside], begin[inside]
        is_rule = symbols >= first_rule
        out[begin[~is_rule] - start] = symbols[~is_rule]
        number = symbols[is_rule] - first_rule
        if visited is not None:
            visited.append(number)
        pairs, at = rules[number], begin[is_rule]
        symbols = pairs.ravel()
        begin = np.stack([at, at + wide[pairs[:, 0]]], 1).ravel()
    return out


# --- encoding --------------------------------------------------------------


def hashes(words: pa.Array) -> np.ndarray:
    """A 64-bit hash of each word of a string array: the sum of its bytes, each mixed with its place."""
    words = plain(words)
    offsets = np.frombuffer(words.buffers()[1], np.int32, len(words) + 1).astype(np.int64)
    data = words.buffers()[2]
    flat = np.frombuffer(data, np.uint8, offsets[-1]) if data is not None else np.zeros(0, np.uint8)
    mixed = np.arange(len(flat)) - np.repeat(offsets[:-1], np.diff(offsets))
    mixed = (mixed << 8 | flat).astype(np.uint64)
    for shift, factor in ((32, 0x9E3779B97F4A7C15), (29, 0xBF58476D1CE4E5B9)):
        mixed *= np.uint64(factor)
        mixed ^= mixed >> np.uint64(shift)
    sums = np.zeros(len(flat) + 1, np.uint64)
    np.cumsum(mixed, out=sums[1:])
    return sums[offsets[1:]] - sums[offsets[:-1]]


class Encoder:
    """Ids by the tokenizers library; each distinct word of a slice is encoded once and remembered for a while.

    The vocabulary's splitting never joins a word with what precedes the space before it, so a text may be cut before
    each space that stands alone, and what lies between may be encoded in any company; the text of another kind of
    vocabulary is one piece. Byte-level ids have known lengths, which lead from the ids of many words to those of each.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        if json.loads(self.tokenizer.to_str())["post_processor"] in (None, {"type": "ByteLevel", "add_prefix_space": True, "trim_offsets": True, "use_regex": True}):
            self.tokenizer.post_processor = None  # it changes offsets only
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        self.first_rule = max(vocab.values()) + 1
        spec = json.loads(self.tokenizer.to_str())
        first = spec["pre_tokenizer"] or {}
        self.cuttable = spec["normalizer"] is None and first.get("type") == "ByteLevel" and first["use_regex"] and not first["add_prefix_space"]
        self.width = np.zeros(self.first_rule, np.int64)  # bytes of each id; a byte is one character in the vocabulary
        for token, i in vocab.items():
            self.width[i] = len(token)
        for token in spec["added_tokens"]:
            self.width[token["id"]] = len(token["content"].encode())
        self._forget()

    def _forget(self) -> None:
        self.known = pa.array([], pa.string())
        self.keys, self.key_of = np.zeros(0, np.uint64), np.zeros(0, np.int32)  # hashes of known words in order, and whose they are
        self.begin, self.size = np.zeros(0, np.int32), np.zeros(0, np.int32)
        self.pool, self.used = np.zeros(1 << 18, np.uint32), 0

    def _encode(self, texts: list[str]) -> list[np.ndarray]:
        out: list[np.ndarray] = []
        a = held = 0
        for b, text in enumerate(texts, 1):
            held += len(text)
            if held >= BATCH_BYTES or b == len(texts):
                out += [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts[a:b], add_special_tokens=False)]
                a, held = b, 0
        return out

    def _learn(self, words: pa.Array) -> None:
        """Put the ids of words not yet known into the pool: each with the space before it, or with its own line break."""
        line = pc.starts_with(words, "\n")
        rest = pc.if_else(line, pc.binary_replace_slice(words, 0, 1, ""), words)
        bare = pc.and_(pc.equal(pc.utf8_trim_whitespace(rest), rest), pc.not_equal(rest, "")).to_numpy(zero_copy_only=False)
        inner = pc.if_else(line, words, pc.binary_join_element_wise("", words, " ")).filter(pa.array(bare))
        wide = pc.binary_length(inner).to_numpy(zero_copy_only=False).astype(np.int64)
        row = np.cumsum(wide) // ROW_BYTES
        cuts = np.r_[0, np.flatnonzero(np.diff(row)) + 1, len(inner)].astype(np.int32) if len(inner) else np.zeros(1, np.int32)
        rows = strings(pc.binary_join(pa.ListArray.from_arrays(pa.array(cuts), inner), ""))
        ids = [np.concatenate([*self._encode(rows), np.zeros(0, np.uint32)])]
        size = np.zeros(len(words), np.int32)
        size[bare] = np.diff(np.r_[0, np.searchsorted(np.cumsum(self.width[ids[0]]), np.cumsum(wide)) + 1])
        begin = np.zeros(len(words), np.int64)
        begin[bare] = np.cumsum(size[bare]) - size[bare]
        if not bare.all():
            odd = self._encode([w if w[:1] == "\n" else " " + w for w in strings(words.filter(pa.array(~bare)))])
            size[~bare] = [len(x) for x in odd]
            begin[~bare] = len(ids[0]) + np.cumsum(size[~bare]) - size[~bare]
            ids += odd
        ids = np.concatenate(ids)
        while self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        self.pool[self.used : self.used + len(ids)] = ids
        self.begin, self.size = np.concatenate([self.begin, (self.used + begin).astype(np.int32)]), np.concatenate([self.size, size])
        self.used += len(ids)
        self.known = pa.concat_arrays([self.known, words])

    def _places(self, words: pa.Array) -> np.ndarray:
        """Where each of the distinct ``words`` is among the known ones.

        Words are found by their hash in a sorted array that grows with them, so a lookup costs by what is asked, not by
        what is known; a word that another of its hash hides is learnt again.
        """
        keys = hashes(words)
        order = np.argsort(keys)
        keys, words = keys[order], words.take(pa.array(order))
        near = np.searchsorted(self.keys, keys)
        place = np.append(self.key_of, 0)[near]
        found = np.append(self.keys, 0)[near] == keys
        found &= near < len(self.keys)
        same = pc.equal(self.known.take(pa.array(place[found])), words.filter(pa.array(found)))
        found[found] = same.to_numpy(zero_copy_only=False)
        if not found.all():
            lack = ~found
            place[lack] = len(self.known) + np.arange(int(lack.sum()))
            self.keys, self.key_of = np.insert(self.keys, near[lack], keys[lack]), np.insert(self.key_of, near[lack], place[lack])
            self._learn(words.filter(pa.array(lack)))
        out = np.empty(len(place), np.int64)
        out[order] = place
        return out

    def _pieces(self, texts: pa.Array) -> pa.Array:
        """Each text as a list of pieces that may be encoded apart; all but the first stand behind a space, or are line breaks of their own."""
        if not self.cuttable:
            return pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32)), texts)
        mixed = pc.match_substring_regex(texts, SPACES).to_numpy(zero_copy_only=False)
        # where all white space stands alone, so does a line break, and is an id of its own
        lists = pc.split_pattern(pc.replace_substring(texts.filter(pa.array(~mixed)), "\n", " \n"), " ")
        if not mixed.any():
            return lists
        others = pa.array([LONE_SPACE.split(t) for t in strings(texts.filter(pa.array(mixed)))], lists.type)
        place = np.empty(len(texts), np.int64)
        place[~mixed], place[mixed] = np.arange(len(lists)), len(lists) + np.arange(len(others))
        return pa.concat_arrays([lists, others]).take(pa.array(place))

    def encode(self, texts: pa.Array, end_id: int | None = None, most: int = SHARD_IDS) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(first text, text after the last, their ids in a row, ids in each) of groups of about ``most`` ids; ``end_id`` is put behind each text."""
        if sum(x.nbytes for x in (self.known, self.keys, self.key_of, self.begin, self.size, self.pool)) > REMEMBERED_BYTES:
            self._forget()
        lists = self._pieces(plain(texts))
        offsets = lists.offsets.to_numpy().astype(np.int64)
        coded = lists.flatten().dictionary_encode()
        first = np.zeros(len(coded), bool)
        first[offsets[:-1][np.diff(offsets) > 0]] = True
        words, codes = coded.dictionary, coded.indices.to_numpy(zero_copy_only=False)
        heads, slot = np.unique(codes[first], return_inverse=True)
        # ids that aren't of a word behind a space stand behind the pool: first words of texts, the end
        extra = [*self._encode(strings(words.take(pa.array(heads)))), np.array([] if end_id is None else [end_id], np.uint32)]
        inner = np.zeros(len(words), bool)
        inner[codes[~first]] = True
        place = np.zeros(len(words), np.int64)
        place[inner] = self._places(words.filter(pa.array(inner)))
        place = place[codes]
        size, begin = (x[place] if len(x) else np.zeros(len(place), np.int32) for x in (self.size, self.begin))
        own = np.fromiter((len(x) for x in extra), np.int32, len(extra))
        at = (self.used + np.cumsum(own) - own).astype(np.int32)
        del place, codes, coded
        size[first], begin[first] = own[slot], at[slot]
        pool = np.concatenate([self.pool[: self.used], *extra])
        ends = offsets[1:] - offsets[0]
        if end_id is not None:
            size, begin = np.insert(size, ends, own[-1]), np.insert(begin, ends, at[-1])
            ends += np.arange(1, len(ends) + 1)
        lens = np.diff(np.r_[0, np.r_[0, np.cumsum(size)][ends]])
        group = (np.cumsum(lens) - lens) // most
        cuts = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(texts)]
        bounds = np.r_[0, ends]
        for a, b in zip(cuts, cuts[1:], strict=False):
            i, j = bounds[a], bounds[b]
            yield a, b, gathered(pool, begin[i:j], size[i:j]), lens[a:b]


def encoder(path: str) -> Encoder:
    """One encoder for each vocabulary file and Python worker."""
    known = memory("encoder")
    if path not in known:
        known[path] = Encoder(path)
    return known[path]


# --- files -----------------------------------------------------------------


def write_ids(docs: DataFrame, vocabulary: str, end_id: int = 0, shard_ids: int = SHARD_IDS) -> tuple[DataFrame, int]:
    """Write the ids of all documents, in ascending doc_id order, as a table of shards; (the table, first rule symbol).

    Parts follow one another by doc_id (null first), shards within a part by ``seq``. Equal doc_ids stand by a hash of
    their texts, by which they may be cut into parts as well. A null text has the end id only.
    """
    rule0 = encoder(vocabulary).first_rule

    def kernel(batches):
        part, seq, before = TaskContext.get().partitionId(), 0, 0
        held: list[tuple] = []

        def shard():
            nonlocal seq, before
            doc_ids, gone, lens, ids = (np.concatenate(x) for x in zip(*held, strict=True))
            symbols, rules = compress(ids, rule0, barrier=end_id)
            row = [part, seq, len(lens), len(ids), before, doc_ids.tobytes(), gone.tobytes(), lens.astype(np.uint32).tobytes(), rules.astype(np.uint32).tobytes()]
            row += [lengths(rules, rule0).astype(np.uint32).tobytes(), (symbols & 0xFFFF).astype(np.uint16).tobytes(), (symbols >> 16).astype(np.uint16).tobytes()]
            seq, before = seq + 1, before + len(ids)
            held.clear()
            return pa.record_batch([pa.array([x], t) for x, t in zip(row, [pa.int32()] * 2 + [pa.int64()] * 3 + [pa.binary()] * 7, strict=True)], names=[c.split()[0] for c in SCHEMA.split(", ")])

        for batch in slices(batches, most=ENCODED_BYTES):
            doc_ids = pc.fill_null(batch.column(0), 0).to_numpy(zero_copy_only=False).astype("<i8")
            gone = pc.is_null(batch.column(0)).to_numpy(zero_copy_only=False).astype(np.uint8)
            for a, b, ids, lens in encoder(vocabulary).encode(batch.column(1), end_id, shard_ids):
                held.append((doc_ids[a:b], gone[a:b], lens, ids))
                if sum(len(x[3]) for x in held) >= shard_ids // 2:
                    yield shard()
        if held:
            yield shard()
        returned()

    spark = docs.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    order = ("doc_id", F.xxhash64("text"))
    ordered = id_and_text(docs).repartitionByRange(n, *order).sortWithinPartitions(*order)
    shared_dir(spark)
    return stored(ordered.mapInArrow(kernel, SCHEMA), "token_ids"), rule0


def grammar_of(row) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(symbols, rules, rule lengths) of a shard given by its fields as buffers."""
    low, high, rules, rule_lens = (np.frombuffer(row[c], t).astype(np.int64) for c, t in (("low", "<u2"), ("high", "<u2"), ("rules", "<u4"), ("rule_lens", "<u4")))
    return low | high << 16, rules.reshape(-1, 2), rule_lens


def read_slice(row, first_rule: int, start: int, stop: int, visited: list | None = None) -> np.ndarray:
    """Ids ``start`` to ``stop`` of one shard, by the rules that cover them only (noted in ``visited``)."""
    return spelled(*grammar_of(row), first_rule, start, stop, visited)


def read_documents(table: DataFrame, first_rule: int) -> DataFrame:
    """``doc_id, start, n_tokens, ids_crc32`` of every document in a table of shards.

    A part's first position needs the ids of the parts before it: one row for each part, as many as shuffle partitions.
    """
    parts = sorted((r["part"], r["n"]) for r in table.groupBy("part").agg(F.sum("n_ids").alias("n")).collect())
    firsts, at = {}, 0
    for part, n in parts:
        firsts[part], at = at, at + n

    def documents_of(row, part: int, before: int) -> pa.RecordBatch:
        view = memoryview(spelled(*grammar_of(row), first_rule).astype("<u4", copy=False)).cast("B")
        lens = np.frombuffer(row["doc_lens"], "<u4").astype(np.int64)
        ends = np.cumsum(lens)
        crc = [zlib.crc32(view[4 * (e - n) : 4 * e]) for n, e in zip(lens.tolist(), ends.tolist(), strict=True)]
        doc = pa.array(np.frombuffer(row["doc_ids"], "<i8"), mask=np.frombuffer(row["no_id"], np.uint8).astype(bool))
        return pa.record_batch([doc, pa.array(ends - lens + (firsts[part] + before)), pa.array(lens), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    def kernel(batches):
        memory("")  # words and vocabulary that writing has left in this worker
        for batch in batches:
            for i in range(batch.num_rows):
                row = {c: batch.column(c)[i].as_buffer() for c in ("doc_ids", "no_id", "doc_lens", "rules", "rule_lens", "low", "high")}
                yield documents_of(row, batch.column("part")[i].as_py(), batch.column("ids_before")[i].as_py())
        returned()

    shards = table.select("part", "ids_before", "doc_ids", "no_id", "doc_lens", "rules", "rule_lens", "low", "high")
    return shards.mapInArrow(kernel, "doc_id long, start long, n_tokens long, ids_crc32 long")
