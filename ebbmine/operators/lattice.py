"""The candidate state of the interval miners, and candidate making.

A set is an integer mask. Its state has two parts, phase (watched, settled) and shape (likely,
unlikely), kept as fields of one record, so a change of state is an update and no move.
The lattice lives on the driver (a record a set ever watched, guarded by max_candidates, which
fails loudly and never truncates); its transactions never do.
"""

from __future__ import annotations

from collections import defaultdict
from dataclasses import dataclass

from ..functions.bits import bits_of

WATCHED, SETTLED, LIKELY, UNLIKELY = "watched", "settled", "likely", "unlikely"


@dataclass(slots=True)
class Entry:
    mask: int
    k: int
    phase: str = WATCHED
    shape: str = UNLIKELY
    supp: int = 0
    stops: int = 0
    born: int = 0
    exact: bool = False  # counted on every chunk


class Lattice:
    def __init__(self, max_candidates: int = 5_000_000):
        self.ledger: dict[int, Entry] = {}  # every set ever watched
        self.limit = max_candidates

    def add(self, mask: int, stop: int, **state) -> Entry:
        if mask in self.ledger:
            raise AssertionError("a set is watched once only")
        if len(self.ledger) >= self.limit:
            raise RuntimeError(f"more than {self.limit} candidate sets; raise minsup or max_candidates, or use the distributed level-wise miner")
        entry = self.ledger[mask] = Entry(mask, mask.bit_count(), born=stop, **state)
        return entry

    def watched(self) -> list[Entry]:
        return [e for e in self.ledger.values() if e.phase == WATCHED]

    def likely(self) -> list[Entry]:
        return [e for e in self.ledger.values() if e.shape == LIKELY]

    def move(self, entry: Entry, phase: str | None = None, shape: str | None = None) -> None:
        """Only unlikely -> likely and watched -> settled."""
        if phase and not (entry.phase == WATCHED and phase == SETTLED):
            raise AssertionError(f"{entry.phase} -> {phase}")
        if shape and not (entry.shape == UNLIKELY and shape == LIKELY):
            raise AssertionError(f"{entry.shape} -> {shape}")
        entry.phase, entry.shape = phase or entry.phase, shape or entry.shape

    def promote(self, need: int) -> list[Entry]:
        up = [e for e in self.watched() if e.shape == UNLIKELY and e.supp >= need]
        for e in up:
            self.move(e, shape=LIKELY)
        return up

    def prune(self, need: int, unseen, supersets: bool = True) -> tuple[int, int]:
        """Settles watched unlikely sets that cannot reach need any more, and their watched unlikely supersets."""
        open_ = [e for e in self.watched() if e.shape == UNLIKELY]
        lost = [e for e in open_ if e.supp + unseen(e) < need]
        for e in lost:
            self.move(e, phase=SETTLED)
        above = 0
        if supersets and lost:
            below = [e.mask for e in lost]
            for e in open_:
                if e.phase == WATCHED and any(e.mask & c == c for c in below):
                    self.move(e, phase=SETTLED)
                    above += 1
        return len(lost), above

    def settle(self, chunks: int) -> int:
        done = [e for e in self.watched() if e.stops == chunks]
        for e in done:
            e.exact = True
            self.move(e, phase=SETTLED)
        return len(done)

    def result(self) -> list[Entry]:
        return [e for e in self.ledger.values() if e.phase == SETTLED and e.shape == LIKELY]


def joined(masks: list[int], known=None) -> set[int]:
    """Unions of sets of equal size k that share all but their highest items."""
    groups = defaultdict(list)
    for x in masks:
        top = 1 << (x.bit_length() - 1)
        groups[x ^ top].append(top)
    out = set()
    for prefix, tops in groups.items():
        for i, a in enumerate(tops):
            base = prefix | a
            for b in tops[i + 1 :]:
                x = base | b
                if known is None or x not in known:
                    out.add(x)
    return out


def passes_subset_test(mask: int, likely: set[int]) -> bool:
    """Whether all sets with one item less are likely."""
    rest = mask
    while rest:
        low = rest & -rest
        if mask ^ low not in likely:
            return False
        rest ^= low
    return True


def make_candidates(lattice: Lattice, promoted: list[Entry], frequent_items: list[int], grow: str = "all", subset_test: bool = True, max_len: int | None = None, group_of: list | None = None) -> list[int]:
    """Masks to watch next: supersets by one item, all of whose immediate subsets are likely, never watched before.

    grow='all' joins all likely sets of equal size (watched or settled); grow='delta' extends only the
    sets promoted at this stop by every likely item: whatever becomes makeable now has one of them below it.
    subset_test=False keeps every join of promoted with likely sets (the ablation).
    """
    likely = {e.mask for e in lattice.ledger.values() if e.shape == LIKELY}
    if grow == "delta":
        items = [1 << p for p in frequent_items if (1 << p) in likely]
        made = {e.mask | b for e in promoted for b in items if not e.mask & b} - lattice.ledger.keys()
    else:
        by_size = defaultdict(list)
        for x in likely:
            by_size[x.bit_count()].append(x)
        fresh = {e.k for e in promoted}
        made = set()
        for k in fresh:  # other sizes have no new likely set below them
            made |= joined(sorted(by_size[k]), lattice.ledger)
    out = []
    for x in made:
        if max_len and x.bit_count() > max_len:
            continue
        if group_of is not None and _crowded(x, group_of):
            continue
        if not subset_test or passes_subset_test(x, likely):
            out.append(x)
    return sorted(out)


def _crowded(mask: int, group_of: list) -> bool:
    """Whether two items of the set belong to one group (at most one item a group is wanted)."""
    seen = [group_of[p] for p in bits_of(mask) if group_of[p] is not None]
    return len(seen) != len(set(seen))
