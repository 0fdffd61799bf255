"""Vertical mining: an item is the list of rows that hold it; unions of sets intersect lists.

Classes by rarest item are searched depth-first, each by one task on its conditional table.
layout: 'tidlist' (sorted row numbers), 'bitmap' (packed bits) or 'diffset' (what a set loses
against its prefix).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame

from . import layout as prepare
from .conditional import search
from .mining import MiningResult, decoded


def _tidlists(need: int, max_len: int):
    def local(held: np.ndarray, weight: np.ndarray) -> dict[int, int]:
        found = {}

        def grow(prefix: int, size: int, tail: list[tuple[int, np.ndarray]]):
            for i, (p, rows) in enumerate(tail):
                mask = prefix | 1 << p
                found[mask] = int(weight[rows].sum())
                if size + 1 < max_len:
                    deeper = []
                    for q, other in tail[i + 1 :]:
                        both = np.intersect1d(rows, other, assume_unique=True)
                        if weight[both].sum() >= need:
                            deeper.append((q, both))
                    if deeper:
                        grow(mask, size + 1, deeper)

        first = [(p, np.flatnonzero(held[:, p])) for p in range(held.shape[1])]
        if max_len > 0:
            grow(0, 0, [(p, r) for p, r in first if weight[r].sum() >= need])
        return found

    return local


def _bitmaps(need: int, max_len: int):
    def local(held: np.ndarray, weight: np.ndarray) -> dict[int, int]:
        found = {}

        def grow(prefix: int, size: int, names: np.ndarray, maps: np.ndarray, supports: np.ndarray):
            for i, p in enumerate(names.tolist()):
                mask = prefix | 1 << p
                found[mask] = int(supports[i])
                if size + 1 < max_len and i + 1 < len(names):
                    both = maps[i + 1 :] & maps[i]
                    s = np.unpackbits(both, axis=1)[:, : len(weight)] @ weight
                    keep = s >= need
                    if keep.any():
                        grow(mask, size + 1, names[i + 1 :][keep], both[keep], s[keep])

        if max_len > 0 and held.shape[1]:
            s = held.T @ weight
            keep = s >= need
            grow(0, 0, np.flatnonzero(keep), np.packbits(held.T[keep], axis=1), s[keep])
        return found

    return local


def _diffsets(need: int, max_len: int):
    def local(held: np.ndarray, weight: np.ndarray) -> dict[int, int]:
        found, total = {}, int(weight.sum())

        def grow(prefix: int, size: int, tail: list[tuple[int, np.ndarray, int]]):
            for i, (p, lost, supp) in enumerate(tail):
                mask = prefix | 1 << p
                found[mask] = supp
                if size + 1 < max_len:
                    deeper = []
                    for q, other, _ in tail[i + 1 :]:
                        more = np.setdiff1d(other, lost, assume_unique=True)  # rows of prefix+p that lack q
                        s = supp - int(weight[more].sum())
                        if s >= need:
                            deeper.append((q, more, s))
                    if deeper:
                        grow(mask, size + 1, deeper)

        first = [(p, np.flatnonzero(~held[:, p])) for p in range(held.shape[1])]
        first = [(p, r, total - int(weight[r].sum())) for p, r in first]
        if max_len > 0:
            grow(0, 0, [x for x in first if x[2] >= need])
        return found

    return local


LAYOUTS = {"tidlist": _tidlists, "bitmap": _bitmaps, "diffset": _diffsets}


def mine(tx: DataFrame, minsup: str | float, layout: str = "bitmap", tids: DataFrame | None = None, only_items: list[str] | None = None, max_len: int | None = None, **_) -> MiningResult:
    e, need = prepare.prepare(tx, minsup, 1, "rank", True, False, tids, only_items)
    found = search(e, LAYOUTS[layout](need, (max_len or 1 << 30) - 1))
    e.release()
    return MiningResult(e.spark, decoded(found, e.items), e.n, need)
