"""Thin-plate splines through many places: sums over all of them by a tree of squares, weights by a preconditioned iteration.

The sum of w_j * r_j^2 * log(r_j) over the places is taken term by term for the places in a square's neighbours; for all others the kernel is
smooth, so weights and values pass through NODES x NODES nodes a square: up the tree, across to squares of the same size that are apart while
the squares around both touch, and down again. The work is in proportion to the places, wherever they crowd.
Weights are found by GMRES; groups of neighbours and a coarse set of places, solved exactly, precondition it. All errors are far below
the digits that are kept, and an iteration that does not get there is an error, not a result.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np

#: Nodes along a square's side, places of a square that is not split at most, and how often squares are split at most.
NODES, FILL, DEPTH = 16, 40, 24
#: The nodes: Chebyshev's in [0, 1].
AT = 0.5 - 0.5 * np.cos(np.pi * (np.arange(NODES) + 0.5) / NODES)
#: Singular values, as shares of the largest, that are left out between squares.
TINY = 1e-15
#: Kernel values between places that are kept from one iteration to the next at most, and that are worked out together.
KEPT, TOGETHER = 40_000_000, 1_000_000
#: Places of a group that is solved by itself, neighbours of each of them that it is solved with, and places of the coarse set at most.
GROUP, OVERLAP, COARSE = 120, 25, 2000
#: Residual relative to the values, iterations between restarts and at most.
SMALL, RESTART, MOST = 1e-8, 50, 200


def kernel(d2: np.ndarray) -> np.ndarray:
    return 0.5 * d2 * np.log(np.maximum(d2, 1e-300))


def _shares(t: np.ndarray) -> np.ndarray:
    """Lagrange polynomials of the nodes at t."""
    out = np.ones((len(t), NODES))
    for k in range(NODES):
        for j in range(NODES):
            if j != k:
                out[:, k] *= (t - AT[j]) / (AT[k] - AT[j])
    return out


def _squared(at: np.ndarray, to: np.ndarray) -> np.ndarray:
    return (at[:, None, 0] - to[None, :, 0]) ** 2 + (at[:, None, 1] - to[None, :, 1]) ** 2


def _grid(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.stack(np.broadcast_arrays(x[:, None], y[None, :]), -1).reshape(-1, 2)


@cache
def _across() -> tuple[np.ndarray, dict[tuple[int, int], tuple[np.ndarray, np.ndarray]]]:
    """A basis for what passes between squares of side 1, and in it, by the step from target to source, the kernel and the squared distances.

    A square of side s has s * s times the kernel and s * s * log(s) times the squared distances.
    """
    own = _grid(AT, AT)
    steps = [(i, j) for i in range(-3, 4) for j in range(-3, 4) if max(abs(i), abs(j)) > 1]
    d2 = {d: _squared(own, own + d) for d in steps}
    left, size, _ = np.linalg.svd(np.hstack([kernel(d2[d]) for d in steps]), full_matrices=False)
    plane = np.column_stack([np.ones(len(own)), own, (own**2).sum(1)])
    q = np.linalg.qr(np.hstack([plane, left[:, size > TINY * size[0]]]))[0]
    return q, {d: (q.T @ kernel(d2[d]) @ q, q.T @ d2[d] @ q) for d in steps}


@cache
def _down() -> list[np.ndarray]:
    """Values at a square's nodes -> values at the nodes of each of its four parts."""
    half = [_shares((AT + k) / 2) for k in (0, 1)]
    return [np.kron(half[k >> 1], half[k & 1]) for k in range(4)]


def _spread(v: np.ndarray) -> np.ndarray:
    """Bits of v at every second place."""
    for shift, mask in ((16, 0x0000FFFF0000FFFF), (8, 0x00FF00FF00FF00FF), (4, 0x0F0F0F0F0F0F0F0F), (2, 0x3333333333333333), (1, 0x5555555555555555)):
        v = (v | (v << shift)) & mask
    return v


def _codes(at: np.ndarray) -> np.ndarray:
    """Numbers of the smallest squares, so that those of a larger square follow each other."""
    i, j = np.clip((at * 2.0**DEPTH).astype(np.int64), 0, 2**DEPTH - 1).T
    return _spread(i) << 1 | _spread(j)


def _ranges(first: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """The numbers of all ranges, one after the other."""
    n = stop - first
    return np.repeat(first - (np.cumsum(n) - n), n) + np.arange(n.sum())


class Level:
    """Squares of one size: their places in the lattice, their ranges of places, and those in four parts, which follow each other at the next level."""

    def __init__(self, k: int, i: np.ndarray, j: np.ndarray, code: np.ndarray, all_codes: np.ndarray, base: int):
        self.k, self.i, self.j, self.code, self.base = k, i, j, code, base
        self.first, self.stop = (np.searchsorted(all_codes, (code + c) << 2 * (DEPTH - k)) for c in (0, 1))
        self.split = (self.stop - self.first > FILL) & (k < DEPTH)
        self.part = np.cumsum(self.split) * 4 - 4
        self.side = 0.5**k

    def parts(self, all_codes: np.ndarray) -> Level:
        four = np.arange(4)
        i, j, code = (v[self.split][:, None] for v in (self.i, self.j, self.code))
        return Level(self.k + 1, (2 * i + (four >> 1)).ravel(), (2 * j + (four & 1)).ravel(), (4 * code + four).ravel(), all_codes, self.base + len(self.code))

    def at(self, where: np.ndarray, box: np.ndarray) -> np.ndarray:
        """Places within the unit square as parts of their squares' sides."""
        return where / self.side - np.column_stack([self.i[box], self.j[box]])

    def nodes(self, box: int) -> np.ndarray:
        return _grid((AT + self.i[box]) * self.side, (AT + self.j[box]) * self.side)


class Plate:
    """Places in the unit square, by a tree of squares: one with more than FILL places is split in four."""

    def __init__(self, places: np.ndarray):
        codes = _codes(places)
        self.order = np.argsort(codes, kind="stable")
        codes, self.places = codes[self.order], places[self.order]
        zero = np.zeros(1, np.int64)
        self.levels = [Level(0, zero, zero, zero, codes, 0)]
        while self.levels[-1].split.any():
            self.levels.append(self.levels[-1].parts(codes))
        self.first, self.stop, self.level = (np.concatenate(v) for v in ([a.first for a in self.levels], [a.stop for a in self.levels], [np.full(len(a.code), a.k) for a in self.levels]))
        self._link()
        self.shares = self._within(self.places, self._leaf(self.places))
        self.w = self.mass = self.field = None

    def _within(self, at: np.ndarray, box: np.ndarray) -> np.ndarray:
        """Shares of each place in the nodes of its square, along both sides."""
        out = np.empty((2, len(at), NODES))
        for a in self.levels:
            own = np.flatnonzero(self.level[box] == a.k)
            out[:, own] = [_shares(t) for t in a.at(at[own], box[own] - a.base).T]
        return out

    def _link(self) -> None:
        """Which squares reach which: far (by level and step), and for those that are not split, places one by one and nodes of smaller squares."""
        self.far, near, nodes, held = [], [], [], np.zeros((0, 2), np.int64)
        a = b = np.zeros(1, np.int64)
        for up, here in zip([None, *self.levels], self.levels):
            if up is not None:
                a, b = (up.part[v][:, None] + np.arange(4) for v in (a, b))
                a, b = a.repeat(4, 1).ravel(), np.tile(b, 4).ravel()
                di, dj = here.i[b] - here.i[a], here.j[b] - here.j[a]
                apart = (np.maximum(np.abs(di), np.abs(dj)) > 1) & (here.stop[b] > here.first[b])
                step = (di + 3) * 7 + dj + 3
                by = np.flatnonzero(apart)[np.argsort(step[apart], kind="stable")]
                cuts = np.flatnonzero(np.diff(step[by], prepend=-1))
                self.far.append([((int(di[r[0]]), int(dj[r[0]])), a[r], b[r]) for r in np.split(by, cuts[1:]) if len(r)])
                beside = np.maximum(np.abs(di), np.abs(dj)) <= 1
                a, b = a[beside], b[beside]
                # what is held by a square that is split goes to its parts
                held = np.column_stack([(up.part[held[:, 0]][:, None] + np.arange(4)).ravel(), held[:, 1].repeat(4)])
            both = here.split[a] & here.split[b]
            one = ~here.split[b]
            held = np.concatenate([held, np.column_stack([a[one], b[one] + here.base])])
            done = ~here.split[held[:, 0]]
            near.append(held[done] + [here.base, 0])
            held = held[~done]
            self._smaller(here, a[~both & ~one], b[~both & ~one], near, nodes)
            a, b = a[both], b[both]
        self.near, self.apart = (self._lists(np.concatenate([np.zeros((0, 2), np.int64), *v])) for v in (near, nodes))

    def _smaller(self, here: Level, a: np.ndarray, b: np.ndarray, near: list, nodes: list) -> None:
        """A square that is not split beside one that is: the parts of that which touch it are looked into, the others are apart."""
        for up, low in zip(self.levels[here.k :], self.levels[here.k + 1 :]):
            if not len(a):
                return
            a, b = a.repeat(4), (up.part[b][:, None] + np.arange(4)).ravel()
            n, times = low.stop[b] - low.first[b], 1 << (low.k - here.k)
            touch = np.ones(len(a), bool)
            for t, s in ((here.i[a], low.i[b]), (here.j[a], low.j[b])):
                touch &= (s >= t * times - 1) & (s <= (t + 1) * times)
            through = ~touch & (n > NODES**2)
            nodes.append(np.column_stack([a + here.base, b + low.base])[through])
            near.append(np.column_stack([a + here.base, b + low.base])[~through & ~(touch & low.split[b]) & (n > 0)])
            a, b = (v[touch & low.split[b]] for v in (a, b))

    def _lists(self, pairs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(first of each square, what it is paired with)."""
        pairs = pairs[np.argsort(pairs[:, 0], kind="stable")]
        return np.searchsorted(pairs[:, 0], np.arange(len(self.first) + 1)), pairs[:, 1]

    def _leaf(self, at: np.ndarray) -> np.ndarray:
        """The square of each place that is not split."""
        codes, box, out = _codes(at), np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
        left = np.arange(len(at))
        for here in self.levels:
            out[left] = box + here.base
            deeper = here.split[box]
            left, box = left[deeper], here.part[box[deeper]]
            box = box + (codes[left] >> 2 * (DEPTH - here.k - 1) & 3) if len(left) else box
        return out

    def load(self, w: np.ndarray) -> Plate:
        """With the weights w (a row for each place, as they were given) and what they make at the nodes, near squares left out."""
        m = w.shape[1]
        self.w = w[self.order]
        self.mass = [np.zeros((len(here.code), m, NODES**2)) for here in self.levels]
        for here, mass in zip(self.levels, self.mass):
            for k in np.flatnonzero(~here.split & (here.stop > here.first)):
                s = slice(here.first[k], here.stop[k])
                ax, ay = self.shares[:, s]
                mass[k] = ((self.w[s, :, None] * ax[:, None, :]).reshape(len(ax), -1).T @ ay).reshape(m, -1)
        for here, mass, low in reversed(list(zip(self.levels, self.mass, self.mass[1:]))):
            mass[here.split] = sum(low[k::4].reshape(-1, NODES**2) @ down for k, down in enumerate(_down())).reshape(-1, m, NODES**2)
        q, steps = _across()
        self.field = [np.zeros_like(self.mass[0])]
        for up, here, mass, far in zip(self.levels, self.levels[1:], self.mass[1:], self.far):
            brief = (mass.reshape(-1, NODES**2) @ q).reshape(len(mass), -1)
            got = np.zeros_like(brief)
            for d, a, b in far:
                plain, square = steps[d]
                got[a] += (brief[b].reshape(-1, q.shape[1]) @ (here.side**2 * (plain + np.log(here.side) * square)).T).reshape(len(a), -1)
            field = (got.reshape(-1, q.shape[1]) @ q.T).reshape(mass.shape)
            for k, down in enumerate(_down()):
                field[k::4] += (self.field[-1][up.split].reshape(-1, NODES**2) @ down.T).reshape(-1, m, NODES**2)
            self.field.append(field)
        return self

    def add(self, other: Plate) -> Plate:
        """With the sums of another one of the same places added. Sums over squares are added, not made again from added weights: those of places
        that nearly meet are large and of both signs, and what a last digit of them makes far away would stay."""
        self.w = self.w + other.w
        self.mass, self.field = ([a + b for a, b in zip(*v)] for v in ((self.mass, other.mass), (self.field, other.field)))
        return self

    def views(self, where: np.ndarray, keep: int = 0) -> Iterator[tuple]:
        """Places in the unit square by square: their rows, their shares in its nodes, places that are taken one by one and, for as many as keep, the kernel."""
        box = self._leaf(where)
        by, shares = np.argsort(box, kind="stable"), self._within(where, box)
        for rows in np.split(by, np.flatnonzero(np.diff(box[by])) + 1) if len(by) else ():
            k = int(box[rows[0]])
            sources = self.near[1][self.near[0][k] : self.near[0][k + 1]]
            sources = _ranges(self.first[sources], self.stop[sources])
            for some in np.array_split(rows, -(-len(rows) * max(len(sources), NODES**2) // TOGETHER)):
                own = where[some]
                keep -= len(some) * len(sources)
                yield some, own, k, shares[:, some], sources, kernel(_squared(own, self.places[sources])) if keep >= 0 else None

    def beside(self, k: int) -> np.ndarray:
        """The k nearest places of each, in the order given, of those in its square and beside it; itself where there are fewer."""
        out = np.repeat(np.arange(len(self.order))[:, None], k, 1)
        for rows, own, _, _, sources, _ in self.views(self.places):
            n = min(k, len(sources))
            near = np.argpartition(_squared(own, self.places[sources]), n - 1, 1)[:, :n]
            out[self.order[rows], :n] = self.order[sources[near]]
        return out

    def at(self, where: np.ndarray, views: list[tuple] | None = None) -> np.ndarray:
        """The sums at places anywhere, a column for each of the weights. views: those of where, if all of it is in the unit square and they are there already."""
        out = np.zeros((len(where), self.w.shape[1]))
        if views is None:
            inside = ((where >= 0) & (where <= 1)).all(1)
            self._outside(where, np.flatnonzero(~inside), out)
            within = np.flatnonzero(inside)
            views = ((within[v[0]], *v[1:]) for v in self.views(where[within]))
        for rows, own, k, (ax, ay), sources, near in views:
            here = self.levels[self.level[k]]
            field = self.field[here.k][k - here.base].reshape(-1, NODES, NODES)
            total = ((ay @ field.reshape(-1, NODES).T).reshape(len(rows), -1, NODES) * ax[:, None, :]).sum(-1)
            for cut in range(0, len(sources), TOGETHER):
                some = sources[cut : cut + TOGETHER]
                total += (kernel(_squared(own, self.places[some])) if near is None else near[:, cut : cut + TOGETHER]) @ self.w[some]
            for far in self.apart[1][self.apart[0][k] : self.apart[0][k + 1]]:
                total += self._through(own, far)
            out[rows] = total
        return out

    def _through(self, where: np.ndarray, box: int) -> np.ndarray:
        """What the places of a square that is apart make, through its nodes."""
        here = self.levels[self.level[box]]
        return kernel(_squared(where, here.nodes(box - here.base))) @ self.mass[here.k][box - here.base].T

    def _outside(self, where: np.ndarray, rows: np.ndarray, out: np.ndarray) -> None:
        """Adds the sums at rows of where that are outside the unit square: from squares that are as far as they are wide, and else from their parts."""
        box = np.zeros(len(rows), np.int64)
        for here in self.levels:
            low = np.column_stack([here.i[box], here.j[box]]) * here.side
            away = np.maximum(low - where[rows], where[rows] - low - here.side).max(1) >= here.side
            n = here.stop[box] - here.first[box]
            through, single = away & (n > NODES**2), (n > 0) & (away & (n <= NODES**2) | ~away & ~here.split[box])
            for take, nodes in ((through, True), (single, False)):
                mine = np.flatnonzero(take)
                mine = mine[np.argsort(box[mine], kind="stable")]
                for group in np.split(mine, np.flatnonzero(np.diff(box[mine])) + 1) if len(mine) else ():
                    k = int(box[group[0]])
                    s = slice(here.first[k], here.stop[k])
                    for some in np.array_split(rows[group], -(-len(group) * NODES**2 // TOGETHER)):
                        out[some] += self._through(where[some], k + here.base) if nodes else kernel(_squared(where[some], self.places[s])) @ self.w[s]
            deeper = ~away & here.split[box]
            rows, box = rows[deeper].repeat(4), (here.part[box[deeper]][:, None] + np.arange(4)).ravel()
            if not len(rows):
                return


def _leaves(places: np.ndarray, size: int) -> list[np.ndarray]:
    """The places in groups of at most that many, by halving the longer side."""
    todo, out = [np.arange(len(places))], []
    while todo:
        rows = todo.pop()
        if len(rows) <= size:
            out.append(rows)
            continue
        at = places[rows]
        half = np.argpartition(at[:, np.argmax(np.ptp(at, axis=0))], len(rows) // 2)
        todo += [rows[half[: len(rows) // 2]], rows[half[len(rows) // 2 :]]]
    return out


def _inverse(at: np.ndarray) -> np.ndarray:
    """Values at the places (then three zeros) -> weights, then the plane."""
    n = len(at)
    m = np.zeros((n + 3, n + 3))
    m[:n, :n] = kernel(((at[:, None] - at[None]) ** 2).sum(-1))
    m[:n, n], m[:n, n + 1 :] = 1.0, at
    m[n:] = m[:, n:].T
    try:
        return np.linalg.inv(m)[:, :n]
    except np.linalg.LinAlgError:  # places on one line
        return np.linalg.pinv(m, hermitian=True)[:, :n]


def solved(places: np.ndarray, values: np.ndarray, nearest) -> tuple[np.ndarray, np.ndarray]:
    """(weights, plane) of the splines through the values (a column each) at different places of the unit square, as of fitted()."""
    plate, plane = fitted(places, values, nearest)
    w = np.empty_like(plate.w)
    w[plate.order] = plate.w
    return w, plane


def fitted(places: np.ndarray, values: np.ndarray, nearest=None) -> tuple[Plate, np.ndarray]:
    """(loaded plate, plane) of the splines through the values (a column each) at different places of the unit square.

    nearest(where, k): the k nearest places of each, nearest first; without it they are found by the plate's squares.
    """
    n, m = values.shape
    parts, plate = [], Plate(places)
    beside = nearest(places, OVERLAP) if nearest else plate.beside(OVERLAP)
    for own in _leaves(places, GROUP):
        near = np.setdiff1d(beside[own].ravel(), own)
        parts.append((own, np.r_[own, near], _inverse(places[np.r_[own, near]])[: len(own)].copy()))
    few = np.array([g[np.argmin(((places[g] - places[g].mean(0)) ** 2).sum(1))] for g in _leaves(places, max(GROUP // 4, -(-n // COARSE)))])
    coarse = _inverse(places[few])
    # every place, and the few, as seen in each iteration
    every, some = list(plate.views(places, KEPT)), list(plate.views(places[few], KEPT))
    ones = np.column_stack([np.ones(n), places])
    flat = np.linalg.qr(ones)[0]

    def spread(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Weights and plane that nearly give c: of each group with its neighbours, then of a few places for what that leaves."""
        w = np.empty((n, m))
        for own, rows, inverse in parts:
            w[own] = inverse @ c[rows]
        w -= flat @ (flat.T @ w)
        rest = coarse @ (c[few] - plate.load(w).at(places[few], some))
        w[few] += rest[:-3]
        return w, rest[-3:]

    def applied(c: np.ndarray) -> np.ndarray:
        w, plane = spread(c)
        return plate.load(w).at(places, every) + ones @ plane

    scale = np.maximum(np.linalg.norm(values, axis=0), 1e-300)
    total, level, done = Plate(places).load(np.zeros((n, m))), np.zeros((3, m)), 0
    left = values.astype(float)
    while (np.linalg.norm(left, axis=0) > SMALL * scale).any():
        if done >= MOST:
            raise ArithmeticError(f"no spline after {MOST} iterations")
        size = np.linalg.norm(left, axis=0)
        basis = [left / np.maximum(size, 1e-300)]
        h = np.zeros((m, RESTART + 1, RESTART))
        for step in range(RESTART):
            v = applied(basis[-1])
            for _ in range(2):
                for k, b in enumerate(basis):
                    dot = (b * v).sum(0)
                    h[:, k, step] += dot
                    v = v - b * dot
            norm = np.linalg.norm(v, axis=0)
            h[:, step + 1, step] = norm
            basis.append(v / np.maximum(norm, 1e-300))
            done += 1
            fits = [np.linalg.lstsq(h[c, : step + 2, : step + 1], np.r_[size[c], np.zeros(step + 1)], rcond=None)[0] for c in range(m)]
            rest = [np.linalg.norm(h[c, : step + 2, : step + 1] @ fits[c] - np.r_[size[c], np.zeros(step + 1)]) for c in range(m)]
            if all(r <= 0.5 * SMALL * s for r, s in zip(rest, scale)):
                break
        w, plane = spread(sum(b * np.array([fits[c][k] for c in range(m)]) for k, b in enumerate(basis[:-1])))
        total.add(plate.load(w))
        level += plane
        left = values - total.at(places, every) - ones @ level
    # not needed where it is only asked for sums, as in tasks it is sent to
    total.shares = total.far = None
    return total, level
