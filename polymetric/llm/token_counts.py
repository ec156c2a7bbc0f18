"""Exact token counts at every prefix by dynamic programming over a merge-ranked vocabulary.

In this kind of vocabulary a token sequence is the encoding of its text exactly when every two neighbours are: so the
encoding of a prefix ends in the one token t that goes with the last token before it, and count(prefix) is
count(prefix without t) + 1. Texts fall into segments no piece crosses (before a run of word marks, around characters
that only stand alone); segments are solved once and kept in a bounded store, and a text's counts are their sums.
"""

from __future__ import annotations

import itertools
import math
import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame

from polymetric.llm.common import worker_store

MARK = "▁"
#: Segments kept by a worker; the store starts anew when it is full.
MOST_KEPT = 2_000_000


class PrefixCounter:
    """Counts for one sentencepiece BPE model with byte fallback, without begin, end or other added tokens."""

    def __init__(self, path: str):
        sp = self.sp = sentencepiece.SentencePieceProcessor(model_file=path)
        normal = [i for i in range(sp.vocab_size()) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.pieces = {sp.id_to_piece(i): -sp.get_score(i) for i in normal}  # the smaller, the sooner merged
        self.longest = max(map(len, self.pieces))
        crossing = re.compile(f"[^{MARK}]{MARK}")
        if any(crossing.search(p) for p in self.pieces) or any("\n" in p and len(p) > 1 for p in self.pieces):
            raise ValueError("a piece crosses a word mark or a line end; segments would not be independent")
        self.ends = {}
        for p in self.pieces:
            self.ends.setdefault(p[-1], set()).add(len(p))
        self.ends = {c: sorted(n, reverse=True) for c, n in self.ends.items()}
        self.goes: dict[tuple[str, str], bool] = {}
        self.totals = _Totals(self)

    def _pair(self, left: str, right: str) -> bool:
        """Whether the two pieces are neighbours in the encoding of their text."""
        key = (left, right)
        if (known := self.goes.get(key)) is None:
            if len(self.goes) >= MOST_KEPT:
                self.goes.clear()
            known = self.goes[key] = self._merged(left + right) == [left, right]
        return known

    def _merged(self, text: str) -> list[str]:
        """Plain merging of a short text by piece rank, leftmost first."""
        parts, rank = list(text), self.pieces
        while len(parts) > 1:
            best, i = min((rank.get(a + b, math.inf), i) for i, (a, b) in enumerate(itertools.pairwise(parts)))
            if best == math.inf:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def segment(self, s: str) -> list[int]:
        """Token counts of the prefixes of one segment, from the empty one to the whole."""
        counts, last, pieces, ends, goes = [0], [""], self.pieces, self.ends, self.goes.get
        for i in range(1, len(s) + 1):
            for n in ends.get(s[i - 1], ()):
                if n > i or (t := s[i - n : i]) not in pieces:
                    continue
                before = last[i - n]
                if before and (ok := goes((before, t))) is not True and (ok is False or not self._pair(before, t)):
                    continue
                counts.append(counts[i - n] + 1)
                last.append(t)
                break
            else:  # bytes of a character without a piece; nothing merges with them
                counts.append(counts[i - 1] + len(s[i - 1].encode("utf-8", "replace")))
                last.append("")
        return counts

    def segments(self, text: str) -> list[str]:
        """The text in the model's form, cut where no piece reaches across."""
        if not text:
            return []
        form = MARK + text.replace(" ", MARK)
        return re.findall(f"\n|{MARK}+[^{MARK}\n]*|[^{MARK}\n]+", form)

    def count(self, text: str) -> int:
        if not text:
            return 0
        form = MARK + text.replace(" ", MARK)
        if MARK + MARK in form:
            return sum(map(self.totals.__getitem__, self.segments(text)))
        lines = form.split("\n")
        words = [w for line in lines for w in _words(line)]
        return sum(map(self.totals.__getitem__, words)) + len(lines) - 1

    def prefixes(self, text: str) -> list[int]:
        """The exact count of every prefix of the text, by number of characters from 0; the first is 0.

        The model puts a word mark before a text, which belongs to the first character.
        """
        out, base = [0], 0
        for k, s in enumerate(self.segments(text)):
            counts = self.segment(s)
            out += [base + c for c in counts[1 + (k == 0) :]]
            base += counts[-1]
        return out

    def fitting(self, text: str, limit: int) -> int:
        """Characters of the longest prefix with at most ``limit`` tokens."""
        parts = self.segments(text)
        sums = [0, *itertools.accumulate(map(self.totals.__getitem__, parts))]
        k = bisect_right(sums, limit) - 1
        chars = sum(map(len, parts[:k])) - (k > 0)
        if k == len(parts):
            return chars
        counts = self.segment(parts[k])
        inside = max(i for i, c in enumerate(counts) if sums[k] + c <= limit)
        return max(0, chars + inside - (k == 0))


def _words(line: str) -> list[str]:
    """Segments of a line without neighbouring marks."""
    first, *rest = line.split(MARK)
    return ([first] if first else []) + [MARK + w for w in rest]


class _Totals(dict):
    """Token counts of whole segments, solved on demand."""

    def __init__(self, counter: PrefixCounter):
        super().__init__()
        self.counter = counter

    def __missing__(self, s: str) -> int:
        if len(self) >= MOST_KEPT:
            self.clear()
        n = self.counter.segment(s)[-1]
        if len(s) <= 64:
            self[s] = n
        return n


def counter(path: str) -> PrefixCounter:
    return worker_store(f"tokens {path}", lambda: PrefixCounter(path))


SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean, fit_chars long"


def count_tokens(docs: DataFrame, model_path: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row a document: UTF-8 bytes, exact tokens, whether they pass ``limit``, and the characters that fit in it.

    Narrow: no shuffle. The vocabulary file must be at ``model_path`` on every executor. A null text counts as empty
    (0 tokens); ids may be null or repeat; other columns are ignored; an empty table gives no rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = counter(model_path)
        for batch in batches:
            size, tokens, fit = [], [], []
            for value in batch.column(1):
                text = value.as_py() or ""
                n = c.count(text)
                size.append(len(text.encode()))
                tokens.append(n)
                fit.append(len(text) if n <= limit else c.fitting(text, limit))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).cast(pa.int64()), pa.array(size, pa.int64()), pa.array(tokens, pa.int64()), pa.array([n > limit for n in tokens], pa.bool_()), pa.array(fit, pa.int64())],
                ["doc_id", "n_bytes", "n_tokens", "over_limit", "fit_chars"],
            )

    return docs.select(id_col, text_col).mapInArrow(run, SCHEMA)
