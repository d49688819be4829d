"""Rank-synchronous merging of many symbol sequences held in flat numpy arrays."""

from __future__ import annotations

import numpy as np

NONE = np.int64(1) << 40


class PairTable:
    """(left, right) -> merged symbol, by open addressing in arrays; rank of a merged symbol by position in `ranks`."""

    def __init__(self, left: np.ndarray, right: np.ndarray, merged: np.ndarray, ranks: np.ndarray):
        size = 1 << max(4, int(np.ceil(np.log2(max(1, len(left)) * 6))))
        self.mask = np.int64(size - 1)
        self.keys = np.full(size, -1, np.int64)
        self.vals = np.full(size, -1, np.int32)
        want = (left.astype(np.int64) << 32) | right.astype(np.int64)
        at, todo = self._home(want), np.arange(len(want))
        while len(todo):
            spot = at[todo]
            free = self.keys[spot] < 0
            self.keys[spot[free]] = want[todo[free]]  # of those at one spot the last stays
            got = self.keys[spot] == want[todo]
            self.vals[spot[got]] = merged[todo[got]]
            todo = todo[~got]
            at[todo] = (at[todo] + 1) & self.mask
        self.ranks = np.append(ranks.astype(np.int64), NONE)  # -1 reads the last: no merge
        own = np.append(np.where(ranks < NONE, ranks, -1), -1)
        #: by rank: all places of it in a sequence may merge at once, as what comes of them ranks later
        late = np.maximum(own[left], own[right]) < self.ranks[merged] if len(left) else np.zeros(0, bool)
        self.early = set(self.ranks[merged[~late]].tolist()) if len(left) else set()

    def _home(self, key: np.ndarray) -> np.ndarray:
        return ((key * np.int64(-7046029254386353131)) >> np.int64(20)) & self.mask

    def find(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = (left.astype(np.int64) << 32) | right.astype(np.int64)
        with np.errstate(over="ignore"):
            at = self._home(key)
        out = np.full(len(key), -1, np.int32)
        seen = self.keys[at]
        hit = seen == key
        out[hit] = self.vals[at[hit]]
        todo = np.flatnonzero(~hit & (seen >= 0))
        while len(todo):
            at[todo] = (at[todo] + 1) & self.mask
            seen = self.keys[at[todo]]
            hit = seen == key[todo]
            out[todo[hit]] = self.vals[at[todo[hit]]]
            todo = todo[~hit & (seen >= 0)]
        return out


def merge(table: PairTable, symbols: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(symbols, lengths) after all merges. In each round every sequence merges its lowest-ranked pair, at the
    leftmost place, or at all places that do not overlap where that gives the same; a sequence without a pair is done."""
    n = len(lengths)
    out_sym: list[np.ndarray] = []
    out_seq: list[np.ndarray] = []
    seq = np.repeat(np.arange(n), lengths)
    sym = symbols.astype(np.int32)
    made = np.full(len(sym), -1, np.int32)
    inner = np.flatnonzero(seq[:-1] == seq[1:])
    made[inner] = table.find(sym[inner], sym[inner + 1])
    early = np.array(sorted(table.early), np.int64)
    while len(sym):
        rank = table.ranks[made]
        first = np.flatnonzero(np.append(True, seq[1:] != seq[:-1]))
        best = np.minimum.reduceat(rank, first)
        own = np.repeat(best, np.diff(np.append(first, len(seq))))
        live = own < NONE
        if not live.all():
            out_sym.append(sym[~live])
            out_seq.append(seq[~live])
            sym, seq, made, rank, own = sym[live], seq[live], made[live], rank[live], own[live]
            if not len(sym):
                break
        hit = rank == own
        at = np.flatnonzero(hit)
        # of places that follow one another without a gap, every second one
        run = np.append(True, np.diff(at) != 1)
        nth = np.arange(len(at)) - np.maximum.accumulate(np.where(run, np.arange(len(at)), 0))
        at = at[nth % 2 == 0]
        if len(early) and len(odd := np.flatnonzero(np.isin(own[at], early))):
            lone = np.ones(len(at), bool)
            of = seq[at]
            lone[odd] = np.append(True, of[1:] != of[:-1])[odd]
            at = at[lone]
        sym[at] = made[at]
        keep = np.ones(len(sym), bool)
        keep[at + 1] = False
        place = np.cumsum(keep) - 1
        sym, seq, made = sym[keep], seq[keep], made[keep]
        at = place[at]
        near = np.zeros(len(sym) + 1, bool)
        near[at] = True
        near[at - 1] = True  # a place before the first is the spare one at the end
        touched = np.flatnonzero(near[:-1])
        made[touched] = -1
        inner = touched[touched < len(sym) - 1]
        inner = inner[seq[inner] == seq[inner + 1]]
        made[inner] = table.find(sym[inner], sym[inner + 1])
    if not out_sym:
        return symbols[:0].astype(np.int32), np.zeros(n, np.int64)
    sym, seq = np.concatenate(out_sym), np.concatenate(out_seq)
    order = np.argsort(seq, kind="stable")
    return sym[order], np.bincount(seq, minlength=n)
