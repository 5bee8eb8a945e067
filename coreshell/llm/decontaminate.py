"""Benchmark decontamination by pigeonhole edit matching.

A test item of m characters may lie in a text with up to k = m * ``error_rate`` edits. Cut into k + 1 pieces, at least
one piece is there unharmed: all pieces of all items form one automaton that finds exact hits in a single pass, and
each hit's surroundings are verified by Myers' bit-parallel edit distance. Case and white space are folded first.

The automaton is made of blocks of items of bounded size, which are broadcast; a benchmark of several blocks (4 million
characters each) takes as many passes of the documents. Rows of text are never shuffled: joining rolling hashes of all
pieces' lengths instead would exchange several rows for each character of the corpus.
"""

from __future__ import annotations

import uuid
from bisect import bisect_right
from collections import defaultdict
from collections.abc import Callable, Iterator

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame

from coreshell.llm.shared import id_and_text, memory, over_slices, slices, stored

ERROR_RATE = 0.06
#: Shortest piece in characters; an item shorter than that must be there without an edit, as whole words.
LEAST_PIECE = 8
#: Characters of items in one automaton; more items are searched for in further passes.
BLOCK_CHARS = 4 << 20


def folded(text: str) -> str:
    return " ".join(text.lower().split())


def folded_places(text: str) -> tuple[str, list[int]]:
    """The folded text and, for each of its characters and its end, the position in ``text``."""
    out, places, space = [], [], False
    lowered = text.lower()
    if len(lowered) != len(text):  # a few capitals have longer small forms
        pieces = [(c, i) for i, c in enumerate(text) for c in c.lower()]
    else:
        pieces = list(zip(lowered, range(len(text)), strict=True))
    for c, i in pieces:
        if c.isspace():
            space = bool(out)
            continue
        if space:
            out.append(" ")
            places.append(places[-1] + 1)
            space = False
        out.append(c)
        places.append(i)
    return "".join(out), [*places, (places[-1] + 1 if places else 0)]


def budget(m: int, error_rate: float) -> int:
    """Edits allowed in an item of ``m`` characters; less than the rate where pieces would be too short."""
    return max(0, min(int(m * error_rate), m // LEAST_PIECE - 1))


def best_end(pattern: str, text: str, anchored: bool = False) -> tuple[int, int]:
    """(distance, end) of the substring of ``text`` nearest to ``pattern``, the leftmost end of equals.

    ``anchored``: of the prefixes of ``text`` only. Myers' algorithm with one big integer for each bit vector.
    """
    masks: dict[str, int] = defaultdict(int)
    for i, c in enumerate(pattern):
        masks[c] |= 1 << i
    m = len(pattern)
    full, top = (1 << m) - 1, 1 << (m - 1)
    plus, minus, now, best, end = full, 0, m, m, 0
    for j, c in enumerate(text, 1):
        eq = masks.get(c, 0)
        diagonal = (((eq & plus) + plus) ^ plus) | eq | minus
        up, down = (minus | ~(diagonal | plus)) & full, plus & diagonal
        if up & top:
            now += 1
        elif down & top:
            now -= 1
        if now < best:
            best, end = now, j
        up, down = (up << 1 | anchored) & full, (down << 1) & full
        vertical = eq | minus
        plus, minus = (down | ~(vertical | up)) & full, up & vertical
    return best, end


class Matcher:
    """The automaton over the pieces of some items."""

    def __init__(self, items: list[tuple[int, str]], error_rate: float):
        self.items, pieces = [], defaultdict(list)
        for item_id, text in items:
            t = folded(text)
            if not (m := len(t)):
                continue
            k = budget(m, error_rate)
            for i in range(k + 1):
                a, b = i * m // (k + 1), (i + 1) * m // (k + 1)
                pieces[t[a:b]].append((len(self.items), a))
            self.items.append((item_id, t, k))
        self.automaton = ahocorasick.Automaton()
        for piece, of in pieces.items():
            self.automaton.add_word(piece, (len(piece), of))
        if pieces:
            self.automaton.make_automaton()

    def find(self, text: str) -> list[tuple[int, int, int, int]]:
        """(item_id, distance, start, end) of each place of a folded text where an item lies within its budget.

        Hits of an item that may belong to one occurrence are verified together; each such stretch yields its best place.
        """
        if not len(self.automaton):
            return []
        starts = defaultdict(set)
        for last, (size, of) in self.automaton.iter(text):
            for item, offset in of:
                starts[item].add(last + 1 - size - offset)
        out = []
        for item, found in starts.items():
            item_id, pattern, k = self.items[item]
            m = len(pattern)
            todo = sorted(found)
            while todo:
                # an occurrence can't overlap another that starts more than its length away
                stretch = [todo[0]]
                while m >= LEAST_PIECE and len(stretch) < len(todo) and todo[len(stretch)] - stretch[-1] <= 2 * k and todo[len(stretch)] - stretch[0] < m:
                    stretch.append(todo[len(stretch)])
                todo = todo[len(stretch) :]
                if m < LEAST_PIECE:
                    whole = [p for p in stretch if text[p - 1 : p] in ("", " ") and text[p + m : p + m + 1] in ("", " ")]
                    out += [(item_id, 0, p, p + m) for p in whole]
                    continue
                exact = next((p for p in stretch if p >= 0 and text.startswith(pattern, p)), None)
                if exact is not None:
                    out.append((item_id, 0, exact, exact + m))
                    todo = todo[bisect_right(todo, exact + m - 1 - k) :]
                    continue
                a, b = max(0, stretch[0] - k), min(len(text), stretch[-1] + m + k)
                distance, end = best_end(pattern, text[a:b])
                if distance <= k:
                    back = best_end(pattern[::-1], text[a : a + end][::-1], anchored=True)[1]
                    out.append((item_id, distance, a + end - back, a + end))
        return sorted(set(out), key=lambda r: (r[2], r[3], r[0]))


def item_blocks(benchmark: DataFrame, block_chars: int = BLOCK_CHARS) -> Iterator[list[tuple[int, str]]]:
    """Items in blocks of bounded size; null texts are none."""
    block, held = [], 0
    for r in benchmark.select(benchmark["item_id"].cast("long").alias("i"), benchmark["text"].alias("t")).where("t is not null").orderBy("i", "t").toLocalIterator():
        block.append((r["i"], r["t"]))
        held += len(r["t"])
        if held >= block_chars:
            yield block
            block, held = [], 0
    if block:
        yield block


def _shared_matcher(docs: DataFrame, items: list[tuple[int, str]], error_rate: float) -> Callable[[], Matcher]:
    """What gives a worker its matcher over one block of items, which is broadcast once to each executor."""
    key, shared = uuid.uuid4().hex, docs.sparkSession.sparkContext.broadcast(items)

    def get() -> Matcher:
        known = memory("matcher")
        if key not in known:
            known.clear()
            known[key] = Matcher(shared.value, error_rate)
        return known[key]

    return get


def _hits(docs: DataFrame, items: list[tuple[int, str]], error_rate: float) -> DataFrame:
    matcher_of = _shared_matcher(docs, items, error_rate)

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        matcher, rows = matcher_of(), []
        for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            if found := matcher.find(folded(text)):
                places = folded_places(text)[1]
                rows += [(doc_id, i, d, places[a], places[b - 1] + 1) for i, d, a, b in found]
        columns = zip(*rows, strict=True) if rows else [[]] * 5
        return pa.record_batch([pa.array(list(c), pa.int64()) for c in columns], names=["doc_id", "item_id", "distance", "start", "end"])

    return over_slices(id_and_text(docs), kernel, "doc_id long, item_id long, distance long, start long, end long", uses="matcher")


def _without(docs: DataFrame, items: list[tuple[int, str]], error_rate: float) -> DataFrame:
    matcher_of, where = _shared_matcher(docs, items, error_rate), docs.columns.index("text")

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        find = matcher_of().find
        return batch.filter(pa.array([not find(folded(t or "")) for t in batch.column(where).to_pylist()], pa.bool_()))

    def run(batches):
        for part in slices(batches, column=where):
            yield kernel(part)

    return docs.mapInArrow(run, docs.schema)


def leaks(docs: DataFrame, benchmark: DataFrame, error_rate: float = ERROR_RATE) -> DataFrame:
    """``doc_id, item_id, distance, start, end`` of every place where a document holds an item within its budget of edits.

    Positions are code points of the text, the end exclusive. Items of fewer than eight folded characters match as whole
    words without edits; empty and null items match nothing; null texts hold nothing; repeated rows and items give
    repeated rows.
    """
    out = None
    for block in item_blocks(benchmark):
        found = _hits(docs, block, error_rate)
        out = found if out is None else out.union(found)
    return out if out is not None else _hits(docs.limit(0), [], error_rate)


def clean(docs: DataFrame, benchmark: DataFrame, error_rate: float = ERROR_RATE) -> DataFrame:
    """The rows of ``docs`` that hold no item, with their columns; each row stays or goes by its own text, whatever its doc_id."""
    out = docs
    for i, block in enumerate(item_blocks(benchmark)):
        # one block's matcher at a time in a worker
        out = _without(stored(out, "clean") if i else out, block, error_rate)
    return out
