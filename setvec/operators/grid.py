"""Products of encodings for a whole grid of settings (bits, projected numbers, repetitions) in one pass over documents.

Signs of a narrower projection are the first rows of a wider one's, so its product is a part of the wider one's: each run of
projected numbers is multiplied once for all settings. A query of a few vectors occupies a few of the cells, so where most are
empty only the occupied ones are multiplied.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from setvec.functions import seeds
from setvec.operators import kernels
from setvec.plans.params import EncodeParams

#: Numbers of documents' blocks that are held at once.
BLOCKS = 1 << 22


class Lists:
    """The best ``k`` documents of each query so far, ties to the smaller id: two arrays (queries, k), whatever their number."""

    def __init__(self, n: int, k: int):
        self.k = k
        self.ids, self.scores = np.full((n, k), -1, np.int64), np.full((n, k), -np.inf, np.float32)

    def add_all(self, ids: np.ndarray, scores: np.ndarray) -> None:
        """Scores (queries, documents) at once; only what reaches a query's k-th best is sorted."""
        floor = self.scores[:, -1]
        if len(ids) > 4 * self.k and (new := floor == -np.inf).any():
            floor = floor.copy()
            floor[new] = np.partition(scores[new], -self.k, axis=1)[:, -self.k]
        row, at = np.nonzero(scores >= floor[:, None])
        if not len(row):
            return
        own, place = np.unique(row, return_inverse=True)
        held = np.repeat(np.arange(len(own)), self.k)
        place = np.concatenate([held, place])
        doc, score = np.concatenate([self.ids[own].ravel(), ids[at]]), np.concatenate([self.scores[own].ravel(), scores[row, at]])
        # Places that are still free sort last.
        order = np.lexsort((doc, -score, doc < 0, place))
        place = place[order]
        first = order[np.arange(len(place)) - np.searchsorted(place, place) < self.k]
        self.ids[own], self.scores[own] = doc[first].reshape(len(own), self.k), score[first].reshape(len(own), self.k)

    def found(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Query's place, id and score of all that is listed."""
        query, at = np.nonzero(self.ids >= 0)
        return query, self.ids[query, at], self.scores[query, at]


class Grid:
    """A block of queries against slices of documents, for all settings (cells, proj, reps)."""

    def __init__(
        self, vecs: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams, bits: tuple[int, ...], projs: tuple[int, ...], reps: tuple[int, ...],
        centers: dict[int, np.ndarray] | None = None,
    ):
        self.owner, self.n, self.params, self.bits, self.projs, self.reps, self.centers = owner, n, params, bits, projs, set(reps), centers
        self.most = max(reps)
        mapped = sorted(p for p in projs if p < params.dim)
        # Runs of coordinates: those of the projections, and then the whole vector.
        ends = mapped + ([mapped[-1] + params.dim if mapped else params.dim] if params.dim in projs else [])
        self.runs = list(zip([0, *ends[:-1]], ends, strict=True))
        self.signs = seeds.inner_signs(params.seed, self.most, mapped[-1], params.dim, params.plane_law).astype(np.float32) if mapped else None
        self.whole = params.dim in projs
        self.vecs = vecs
        self.cells = self._cells(vecs)

    @property
    def step(self) -> int:
        """Documents at once."""
        return max(1, BLOCKS // ((1 << max(self.bits)) * self.runs[-1][1]))

    def _cells(self, vecs: np.ndarray) -> np.ndarray | None:
        return None if self.centers else np.ascontiguousarray(kernels.cells_of(vecs, self.params.with_(hash_bits=max(self.bits), reps=self.most, proj_dim=self.params.dim)).T)

    def _code(self, vecs: np.ndarray, cells: np.ndarray | None, bits: int, rep: int) -> np.ndarray:
        return kernels.nearest_center(vecs, self.centers[1 << bits][rep]) if self.centers else cells[rep] & ((1 << bits) - 1)

    def _mapped(self, vecs: np.ndarray, rep: int) -> np.ndarray:
        """Projected vectors, and themselves if a setting has no projection."""
        parts = ([] if self.signs is None else [vecs @ self.signs[rep].T]) + ([vecs] if self.whole else [])
        return np.concatenate(parts, axis=-1)

    def _documents(self, vecs: np.ndarray, points: np.ndarray, code: np.ndarray, owner: np.ndarray, n: int, bits: int, rep: int) -> np.ndarray:
        """Blocks (n, cells, coordinates) of one repetition, filled."""
        cells = 1 << bits
        if self.centers:
            own = self.params.with_(partition="center", n_centers=cells, reps=self.most, proj_dim=self.params.dim)
            return self._mapped(kernels.rep_blocks(vecs, code, owner, n, own, self.centers[cells][rep], True).astype(np.float32), rep)
        own = self.params.with_(hash_bits=bits, reps=self.most, proj_dim=self.params.dim)
        out = np.zeros((n * cells, points.shape[1]), np.float32)
        # Two bytes, where they do, sort fastest.
        base = (owner * cells).astype(np.uint16 if n * cells <= 1 << 16 else np.int64)
        kernels._put_blocks(out, 0, cells, n, points, code, np.arange(len(code)), base, own, True)
        return out.reshape(n, cells, -1)

    def _asked(self, points: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Occupied blocks of the queries, by cell: cell, query, sum."""
        flat = code * self.n + self.owner
        order = np.argsort(flat, kind="stable")
        firsts = np.flatnonzero(np.diff(flat[order], prepend=-1))
        sizes, key = np.diff(firsts, append=len(flat)), flat[order][firsts]
        # Most blocks are of one vector.
        total = points[order[firsts]]
        for r in range(1, sizes.max(initial=1)):
            more = np.flatnonzero(sizes > r)
            total[more] += points[order[firsts[more] + r]]
        return key // self.n, key % self.n, total

    def scores(self, vecs: np.ndarray, owner: np.ndarray, n: int) -> Iterator[tuple[tuple[int, int, int], np.ndarray]]:
        """Setting, and products (queries, n) with a slice of documents."""
        cells_of, params = self._cells(vecs), self.params
        for bits in self.bits:
            cells, total = 1 << bits, [np.zeros((self.n, n), np.float32) for _ in self.runs]
            for rep in range(self.most):
                blocks = self._documents(vecs, self._mapped(vecs, rep), self._code(vecs, cells_of, bits, rep), owner, n, bits, rep)
                cell, query, asked = self._asked(self._mapped(self.vecs, rep), self._code(self.vecs, self.cells, bits, rep))
                if 2 * len(cell) >= self.n * cells:
                    whole = np.zeros((self.n, cells, blocks.shape[2]), np.float32)
                    whole[query, cell] = asked
                    for own, (lo, hi) in zip(total, self.runs, strict=True):
                        own += whole[:, :, lo:hi].reshape(self.n, -1) @ blocks[:, :, lo:hi].reshape(n, -1).T
                else:
                    cuts = np.searchsorted(cell, np.arange(cells + 1))
                    for c in np.flatnonzero(np.diff(cuts)).tolist():
                        part = slice(cuts[c], cuts[c + 1])
                        for own, (lo, hi) in zip(total, self.runs, strict=True):
                            own[query[part]] += asked[part, lo:hi] @ blocks[:, c, lo:hi].T
                if rep + 1 in self.reps:
                    for p in self.projs:
                        if p == params.dim:
                            yield (cells, p, rep + 1), total[-1]
                        else:
                            yield (cells, p, rep + 1), sum(own for own, (_, hi) in zip(total, self.runs, strict=True) if hi <= p) / np.float32(p)
