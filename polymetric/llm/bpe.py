"""Byte-level BPE: a priority queue of merge ranks over a doubly linked list of symbols (of a short word: the least rank of a plain
list), and decoding by concatenating vocabulary strings."""

from __future__ import annotations

import hashlib
import heapq
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from polymetric.llm.common import give_back, worker_store

#: Words kept by a worker in each of two generations: the older one goes when the younger is full.
MOST_KEPT = 100_000
#: Bytes of a word up to which the pair to merge is found in a plain list, and what stands there for a pair that doesn't merge.
SHORT, NONE = 64, 1 << 62
#: The pattern that cuts a text into words, as the vocabulary's users publish it.
WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+")


def byte_letters() -> dict[int, str]:
    """The printable letter that stands for each byte in the vocabulary: itself if printable, else the next free one from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = iter(range(256, 512))
    return {b: chr(b if b in plain else next(others)) for b in range(256)}


class _Ids(dict):
    """Little-endian ids of words, encoded on demand. Words that recur outlive a full store."""

    def __init__(self, bpe: BytePairs):
        super().__init__()
        self.bpe, self.older = bpe, {}

    def __missing__(self, word: str) -> bytes:
        ids = self.older.get(word) or np.array(self.bpe.merge(word), "<u4").tobytes()
        if len(word) <= 64:
            if len(self) >= MOST_KEPT:
                self.older = dict(self)
                self.clear()
            self[word] = ids
        return ids


class BytePairs:
    """A byte-level BPE vocabulary in the tokenizers library's JSON form."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        vocab = data["model"]["vocab"]
        letters = byte_letters()
        back = {c: b for b, c in letters.items()}
        self.start = [vocab[letters[b]] for b in range(256)]
        self.merges: dict[tuple[int, int], int] = {}
        for rank, pair in enumerate(data["model"]["merges"]):
            a, b = pair.split(" ") if isinstance(pair, str) else pair
            self.merges[vocab[a], vocab[b]] = rank << 32 | vocab[a + b]
        added = {t["content"]: t["id"] for t in data["added_tokens"]}
        self.added = {c: np.array([i], "<u4").tobytes() for c, i in added.items()}
        self.special = regex.compile("(" + "|".join(regex.escape(c) for c in sorted(added, key=len, reverse=True)) + ")") if added else None
        self.bytes_of = [b""] * (max([*vocab.values(), *added.values()]) + 1)
        for piece, i in [*vocab.items(), *added.items()]:
            self.bytes_of[i] = bytes(back[c] for c in piece) if all(c in back for c in piece) else piece.encode()
        self.strings = pa.array(self.bytes_of, pa.large_binary())
        self.ids = _Ids(self)
        del data, vocab
        give_back()

    def merge(self, word: str) -> list[int]:
        """Ids of one word. Symbols form a doubly linked list; the queue holds (rank, place, left, right) of pairs,
        and an entry is stale once either symbol changed."""
        start, merges = self.start, self.merges
        sym = [start[b] for b in word.encode()]
        n = len(sym)
        if n <= SHORT:
            return self.merge_short(sym)
        prev, nxt = list(range(-1, n - 1)), [*range(1, n), -1]
        queue = [(m, i, a, b) for i, (a, b) in enumerate(zip(sym, sym[1:], strict=False)) if (m := merges.get((a, b))) is not None]
        heapq.heapify(queue)
        while queue:
            m, i, a, b = heapq.heappop(queue)
            j = nxt[i]
            if sym[i] != a or j < 0 or sym[j] != b:
                continue
            made = m & 0xFFFFFFFF
            sym[i], sym[j] = made, -1
            k = nxt[i] = nxt[j]
            if k >= 0:
                prev[k] = i
                if (m := merges.get((made, sym[k]))) is not None:
                    heapq.heappush(queue, (m, i, made, sym[k]))
            if (h := prev[i]) >= 0 and (m := merges.get((sym[h], made))) is not None:
                heapq.heappush(queue, (m, h, sym[h], made))
        return [s for s in sym if s >= 0]

    def merge_short(self, sym: list[int]) -> list[int]:
        """The same order of merges, least rank first and leftmost of equal ones, by the least of a plain list of the pairs' ranks."""
        merge = self.merges.get
        ranks = [merge(p, NONE) for p in zip(sym, sym[1:], strict=False)]
        while ranks and (m := min(ranks)) != NONE:
            i = ranks.index(m)
            sym[i : i + 2] = (m & 0xFFFFFFFF,)
            del ranks[i]
            if i < len(ranks):
                ranks[i] = merge((sym[i], sym[i + 1]), NONE)
            if i:
                ranks[i - 1] = merge((sym[i - 1], sym[i]), NONE)
        return sym

    def encode(self, text: str) -> np.ndarray:
        """Ids of a text; strings of added tokens become these tokens."""
        get, out = self.ids.__getitem__, []
        if self.special is None or not any(c in text for c in self.added):
            out = map(get, WORDS.findall(text))
        else:
            for part in self.special.split(text):
                out += [self.added[part]] if part in self.added else map(get, WORDS.findall(part))
        return np.frombuffer(b"".join(out), "<u4")

    def decode(self, ids: np.ndarray) -> str:
        _, ends, joined = self.strings.take(pa.array(ids)).buffers() if len(ids) else (None, None, None)
        return str(memoryview(joined)[: np.frombuffer(ends, "<i8")[len(ids)]], "utf-8", "replace") if joined else ""


def vocabulary(path: str) -> BytePairs:
    return worker_store(f"bpe {path}", lambda: BytePairs(path))


SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def encode_documents(docs: DataFrame, path: str, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row a document: number of ids, the SHA-256 of the ids and of the text decoded from them (with_ids: the ids too).

    Narrow: no shuffle. The vocabulary file must be at ``path`` on every executor. A null text counts as empty (no
    ids); ids may be null or repeat; other columns are ignored; an empty table gives no rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = vocabulary(path)
        for whole in batches:
            for start in range(0, len(whole), 256):  # a few texts at a time, so the ids of a batch don't add up
                batch = whole.slice(start, 256)
                n, shas, texts, lists = [], [], [], []
                for value in batch.column(1):
                    ids = bpe.encode(value.as_py() or "")
                    n.append(len(ids))
                    shas.append(hashlib.sha256(ids.tobytes()).hexdigest())
                    texts.append(hashlib.sha256(bpe.decode(ids).encode()).hexdigest())
                    if with_ids:
                        lists.append(ids.astype(np.int32))
                cols = [batch.column(0).cast(pa.int64()), pa.array(n, pa.int64()), pa.array(shas, pa.string()), pa.array(texts, pa.string())]
                names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
                if with_ids:
                    cols.append(pa.array(lists, pa.list_(pa.int32())))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names)

    return docs.select(id_col, text_col).mapInArrow(run, SCHEMA + (", ids array<int>" if with_ids else ""))
