"""Token counts by byte-pair merging over a linked list of symbols with a heap of adjacent pairs.

No identifiers leave the kernel: a piece has as many tokens as it has initial
symbols, less one for each merge. Only distinct white-space separated words of a
slice are merged; each worker keeps a bounded cache.
"""

from __future__ import annotations

import heapq
import json
import unicodedata

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame

from coreshell.llm.shared import id_and_text, memory, over_slices, strings, word_codes

#: Words whose counts a worker remembers at most; beyond it the memory starts anew.
REMEMBERED = 400_000


def byte_symbols() -> list[str]:
    """The printable character that byte-level vocabularies use for each byte."""
    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    out, spare = {b: chr(b) for b in shown}, 256
    for b in range(256):
        if b not in out:
            out[b], spare = chr(spare), spare + 1
    return [out[b] for b in range(256)]


class MergeCounter:
    """Counts tokens as the tokenizers library does for a BPE vocabulary with word ends, NFC, lower case and dropped white space."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, self.suffix = spec["model"], spec["model"]["end_of_word_suffix"] or ""
        vocab = model["vocab"]
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.wide = 1 << max(vocab.values()).bit_length()
        self.ranks = {vocab[a] * self.wide + vocab[b]: (rank, vocab[a + b]) for rank, (a, b) in enumerate(pairs)}
        symbols = byte_symbols()
        self.inner = [vocab[s] for s in symbols]
        self.last = [vocab[s + self.suffix] for s in symbols]
        self.special = [t["content"] for t in spec["added_tokens"] if not t["normalized"]]
        self.special_at = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        splitter = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pieces = regex.compile(splitter)
        self.known: dict[str, int] = {}

    def merged(self, data: bytes) -> int:
        """Tokens of one piece."""
        n = len(data)
        if n < 2:
            return n
        sym = [self.inner[b] for b in data]
        sym[-1] = self.last[data[-1]]
        before, after = list(range(-1, n - 1)), [*range(1, n), -1]
        ranks, wide, heap = self.ranks, self.wide, []
        for i in range(n - 1):
            if (hit := ranks.get(sym[i] * wide + sym[i + 1])) is not None:
                heap.append((hit[0], i, hit[1]))
        heapq.heapify(heap)
        left = n
        while heap:
            rank, i, new = heapq.heappop(heap)
            j = after[i] if sym[i] >= 0 else -1
            if j < 0 or (hit := ranks.get(sym[i] * wide + sym[j])) is None or hit[0] != rank:
                continue  # one of the two symbols has gone into another merge since
            sym[i], sym[j], left = new, -1, left - 1
            after[i] = k = after[j]
            if k >= 0:
                before[k] = i
                if (hit := ranks.get(new * wide + sym[k])) is not None:
                    heapq.heappush(heap, (hit[0], i, hit[1]))
            if (h := before[i]) >= 0 and (hit := ranks.get(sym[h] * wide + new)) is not None:
                heapq.heappush(heap, (hit[0], h, hit[1]))
        return left

    def _plain(self, text: str) -> int:
        text = unicodedata.normalize("NFC", text).replace("Σ", "σ").lower()  # the library lowers sigma without its context
        return sum(self.merged(p.encode("utf-8")) for p in self.pieces.findall(text))

    def count(self, text: str) -> int:
        """Tokens of any text; special strings count one each."""
        if self.special_at is None or "<|" not in text and not self.special_at.search(text):
            return self._plain(text)
        return sum(self._plain(p) for p in self.special_at.split(text)) + sum(1 for _ in self.special_at.finditer(text))

    def word(self, word: str) -> int:
        if (n := self.known.get(word)) is None:
            if len(self.known) >= REMEMBERED:
                self.known.clear()
            n = self.known[word] = self.count(word)
        return n


def counter(path: str) -> MergeCounter:
    """One counter for each vocabulary file and Python worker."""
    known = memory("merges")
    if path not in known:
        known[path] = MergeCounter(path)
    return known[path]


def count_tokens(docs: DataFrame, vocabulary: str, limit: int = 2048) -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` of every document, whole texts.

    A null or empty text has 0 tokens; repeated rows are counted each; a null doc_id stays null.
    ``vocabulary`` is a file that each executor has (part of the installed tokenizers package).
    """

    def kernel(batch: pa.RecordBatch) -> pa.RecordBatch:
        texts = batch.column(1)
        merges = counter(vocabulary)
        where, codes, words = word_codes(texts)
        each = np.fromiter((merges.word(w) for w in strings(words)), np.int64, len(words))
        n = np.bincount(where, weights=each[codes], minlength=len(texts)).astype(np.int64)
        # separators that only Arrow takes for white space
        for i in np.flatnonzero(pc.match_substring_regex(texts, "[\x1c-\x1f]").to_numpy(zero_copy_only=False)):
            n[i] = merges.count(texts[int(i)].as_py())
        return pa.record_batch([batch.column(0), pc.cast(pc.binary_length(texts), pa.int64()), pa.array(n), pa.array(n > limit)], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return over_slices(id_and_text(docs), kernel, "doc_id long, n_bytes long, n_tokens long, over_limit boolean", uses="merges")
