"""Trees over pivot vectors of a sample, on the driver: an R*-tree by insertion, sort-tile-recursive packing, median splits."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import numpy as np


@dataclass
class Node:
    leaf: bool
    lo: np.ndarray
    hi: np.ndarray
    kids: list = field(default_factory=list)  # vectors in a leaf, nodes above


def _box(kids: list, leaf: bool) -> tuple[np.ndarray, np.ndarray]:
    low = np.array([k if leaf else k.lo for k in kids])
    high = low if leaf else np.array([k.hi for k in kids])
    return low.min(axis=0), high.max(axis=0)


class RStarTree:
    """Choose-subtree by least overlap growth above leaves (else least enlargement), one forced reinsertion a level,
    splits by least margin, then least overlap."""

    def __init__(self, dims: int, most: int = 32, fill: float = 0.4, reinsert: float = 0.3):
        self.most, self.least, self.again = most, max(1, int(fill * most)), max(1, int(reinsert * most))
        self.root = Node(True, np.full(dims, np.inf), np.full(dims, -np.inf))

    def insert(self, v: np.ndarray) -> None:
        work, spared = [np.asarray(v, float)], False
        while work:
            over = self._put(work.pop(), may_reinsert=not spared)
            if over:
                spared = True
                work += over

    def _choose(self, node: Node, v: np.ndarray) -> Node:
        lo, hi = np.array([k.lo for k in node.kids]), np.array([k.hi for k in node.kids])
        nlo, nhi = np.minimum(lo, v), np.maximum(hi, v)
        area, grown = np.prod(hi - lo, axis=1), np.prod(nhi - nlo, axis=1)
        if node.kids[0].leaf:
            def overlap(a: np.ndarray, b: np.ndarray) -> np.ndarray:
                side = np.minimum(b[:, None], hi[None]) - np.maximum(a[:, None], lo[None])
                each = np.prod(np.clip(side, 0, None), axis=2)
                return each.sum(axis=1) - np.diagonal(each)
            keys = (area, grown - area, overlap(nlo, nhi) - overlap(lo, hi))
        else:
            keys = (area, grown - area)
        return node.kids[int(np.lexsort(keys)[0])]

    def _put(self, v: np.ndarray, may_reinsert: bool) -> list[np.ndarray]:
        path, node = [], self.root
        while not node.leaf:
            path.append(node)
            node = self._choose(node, v)
        node.kids.append(v)
        out: list[np.ndarray] = []
        if len(node.kids) > self.most and may_reinsert and path:
            far = np.argsort(-np.linalg.norm(np.array(node.kids) - (node.lo + node.hi) / 2, axis=1), kind="stable")[: self.again].tolist()
            out = [node.kids[i] for i in far]
            node.kids = [k for i, k in enumerate(node.kids) if i not in set(far)]
        for up in reversed([*path, node]):
            up.lo, up.hi = _box(up.kids, up.leaf)
            if len(up.kids) > self.most:
                a, b = self._split(up)
                parent = next((p for p in path if any(k is up for k in p.kids)), None) if up is not self.root else None
                if parent is None:
                    self.root = Node(False, np.minimum(a.lo, b.lo), np.maximum(a.hi, b.hi), [a, b])
                else:
                    parent.kids = [k for k in parent.kids if k is not up] + [a, b]
        return out

    def _split(self, node: Node) -> tuple[Node, Node]:
        best = None
        for axis in range(len(node.lo)):
            kids = sorted(node.kids, key=lambda k: (k[axis] if node.leaf else (k.lo[axis], k.hi[axis])))
            options = []
            for cut in range(self.least, len(kids) - self.least + 1):
                (alo, ahi), (blo, bhi) = _box(kids[:cut], node.leaf), _box(kids[cut:], node.leaf)
                margin = (ahi - alo).sum() + (bhi - blo).sum()
                options.append((np.prod(np.clip(np.minimum(ahi, bhi) - np.maximum(alo, blo), 0, None)), np.prod(ahi - alo) + np.prod(bhi - blo), cut, margin))
            total = sum(o[3] for o in options)
            if best is None or total < best[0]:
                best = (total, kids, min(options)[2])
        _, kids, cut = best
        return tuple(Node(node.leaf, *_box(part, node.leaf), part) for part in (kids[:cut], kids[cut:]))

    def leaves(self) -> list[Node]:
        out, work = [], [self.root]
        while work:
            node = work.pop()
            if node.leaf:
                out.append(node)
            else:
                work += node.kids
        return out

    def walk(self, a: np.ndarray, w: np.ndarray, r: float) -> list[Node]:
        """Leaves whose boxes are within r by weighted gaps; whole subtrees are skipped."""
        out, work = [], [self.root]
        while work:
            node = work.pop()
            if (w * np.clip(np.maximum(node.lo - a, a - node.hi), 0, None)).sum() <= r:
                if node.leaf:
                    out.append(node)
                else:
                    work += node.kids
        return out


def str_pack(x: np.ndarray, most: int, axis: int = 0) -> list[np.ndarray]:
    """Groups of rows by sorting and tiling one dimension after another."""
    if len(x) <= most:
        return [x]
    dims = x.shape[1]
    x = x[np.argsort(x[:, axis], kind="stable")]
    left = dims - axis
    tiles = math.ceil((len(x) / most) ** (1 / left)) if left > 1 else math.ceil(len(x) / most)
    parts = np.array_split(x, max(2, tiles))
    return [g for p in parts for g in (str_pack(p, most, axis + 1) if left > 1 else [p])]


def kd_splits(x: np.ndarray, depth: int) -> list[tuple[int, int, float]]:
    """(node, dimension, value) of median splits of the widest dimension; node k has children 2k + 1 and 2k + 2."""
    out, work = [], [(0, x, 0)]
    while work:
        k, part, d = work.pop()
        if d == depth or len(part) < 2:
            continue
        axis = int(np.argmax(part.std(axis=0)))
        cut = float(np.median(part[:, axis]))
        low = part[:, axis] <= cut
        if low.all() or not low.any():
            continue
        out.append((k, axis, cut))
        work += [(2 * k + 1, part[low], d + 1), (2 * k + 2, part[~low], d + 1)]
    return sorted(out)
