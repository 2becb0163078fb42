"""Array kernels: cells, blocks, fill, projections and MaxSim for many bags at once.

Vectors of all bags of a batch lie stacked, with each one's bag number beside it, ascending. In fixed arithmetic all
arrays are 64-bit whole numbers; otherwise 32-bit floats.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache

import numpy as np

from setvec.functions import seeds
from setvec.plans.params import BUILT_IN, EncodeParams

#: Numbers that a slice of bags may hold in its blocks at once.
SLICE = 1 << 23
#: Vectors of a cell that are added one after another for all cells at once.
LONG = 64
#: Bags whose blocks of a repetition are made and multiplied at once.
AT_ONCE = 256
#: Products that a scan holds at once.
TILE = 1 << 21


#: Cells by name: (vectors, params) -> cell numbers (vectors, repetitions) below ``params.cells``. Sign cells and centres are
#: built in; any locality-sensitive partition may be added by ``register_partition``.
PARTITIONS: dict[str, Callable[[np.ndarray, EncodeParams], np.ndarray]] = {}


def register_partition(name: str, cells: Callable[[np.ndarray, EncodeParams], np.ndarray]) -> None:
    """Adds a partition of space; ``EncodeParams(partition=name, n_centers=...)`` gives its number of cells. Empty cells of
    a document are filled by the vector whose cell number differs in the fewest bits, as with sign cells."""
    if name in BUILT_IN:
        raise ValueError(f"{name!r} is built in")
    PARTITIONS[name] = cells


def axis_cells(vecs: np.ndarray, params: EncodeParams) -> np.ndarray:
    """Cells by the longest axis after a random rotation, and its sign: twice as many cells as axes."""
    axes = params.n_centers // 2
    out = []
    for rep in range(params.reps):
        turned = vecs @ seeds.generator("plane", params.seed, rep).standard_normal((axes, params.dim)).astype(vecs.dtype).T
        top = np.abs(turned).argmax(1)
        out.append(2 * top + (turned[np.arange(len(vecs)), top] > 0))
    return np.stack(out, 1)


def number_type(params: EncodeParams) -> type:
    return np.int64 if params.arithmetic == "fixed" else np.float32


@lru_cache(maxsize=16)
def hamming(cells: int) -> np.ndarray:
    codes = np.arange(cells)
    return np.bitwise_count(codes[:, None] ^ codes[None, :]).astype(np.int64)


@lru_cache(maxsize=16)
def _by_distance(cells: int) -> list[np.ndarray]:
    """Numbers that change a code in one bit, in two, and so on."""
    codes = np.arange(1, 1 << max(1, (cells - 1).bit_length()))
    count = np.bitwise_count(codes)
    return [codes[count == c] for c in range(1, int(count.max()) + 1)]


def cells_of(vecs: np.ndarray, params: EncodeParams, centers: np.ndarray | None = None) -> np.ndarray:
    """Cell of each vector in each repetition. A sign bit is set for products strictly above 0; a tie between centres
    goes to the lower number."""
    if params.partition == "center":
        if centers is None:
            raise ValueError("a centre partition needs its centres")
        return np.stack([nearest_center(vecs, c) for c in centers], 1)
    if params.partition not in BUILT_IN:
        return PARTITIONS[params.partition](vecs, params)
    if not params.hash_bits:
        return np.zeros((len(vecs), params.reps), np.int64)
    planes = seeds.planes(params.seed, params.reps, params.hash_bits, params.dim, params.plane_law)
    bits = (vecs @ planes.reshape(-1, params.dim).T.astype(vecs.dtype)) > 0
    # By floats, which hold so few bits exactly: products of whole numbers are many times slower.
    weights = (1 << np.arange(params.hash_bits)).astype(np.float32)
    return (bits.reshape(-1, params.hash_bits).astype(np.float32) @ weights).reshape(len(vecs), params.reps).astype(np.int64)


def nearest_center(vecs: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """By squared distance; 2 v.c - c.c is largest at the nearest."""
    score = 2 * (vecs @ centers.T) - (centers * centers).sum(1)
    return score.argmax(1)


def _blocks(vecs: np.ndarray, code: np.ndarray, owner: np.ndarray, n: int, cells: int) -> tuple[np.ndarray, np.ndarray]:
    """Sum (n, cells, dim) and count (n, cells) of the vectors of each bag and cell."""
    flat = owner * cells + code
    order = np.argsort(flat, kind="stable")
    total = np.zeros((n * cells, vecs.shape[1]), vecs.dtype)
    if len(flat):
        firsts = np.flatnonzero(np.diff(flat[order], prepend=-1))
        total[flat[order][firsts]] = np.add.reduceat(vecs[order], firsts, axis=0)
    return total.reshape(n, cells, -1), np.bincount(flat, minlength=n * cells).reshape(n, cells)


def _fill(total: np.ndarray, count: np.ndarray, vecs: np.ndarray, code: np.ndarray, owner: np.ndarray, params: EncodeParams, centers: np.ndarray | None) -> None:
    """Gives every empty cell of a bag one vector of the bag: that whose code differs in the fewest bits (or, of a centre
    partition, that nearest to the cell's centre); a tie goes to the smallest place. Works in place."""
    n, cells = count.shape
    empty_bag, empty_cell = np.nonzero((count == 0) & (count.sum(1) > 0)[:, None])
    if not len(empty_bag):
        return
    if params.partition == "center":
        starts = np.searchsorted(owner, np.arange(n + 1))
        for bag in np.unique(empty_bag):
            own = vecs[starts[bag] : starts[bag + 1]]
            holes = empty_cell[empty_bag == bag]
            far = (own * own).sum(1)[None, :] - 2 * (centers[holes] @ own.T)
            total[bag, holes] = own[far.argmin(1)]
        return
    first = np.full(n * cells, len(vecs), np.int64)
    np.minimum.at(first, owner * cells + code, np.arange(len(vecs)))
    first = first.reshape(n, cells)
    cost = hamming(cells)[empty_cell] * (len(vecs) + 1) + first[empty_bag]
    cost[count[empty_bag] == 0] = np.iinfo(np.int64).max
    total[empty_bag, empty_cell] = vecs[first[empty_bag, cost.argmin(1)]]


def rep_blocks(vecs: np.ndarray, code: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams, centers: np.ndarray | None, document: bool) -> np.ndarray:
    """Blocks (n, cells, dim) of one repetition before any projection: a query's sums, or a document's means with its empty
    cells filled."""
    total, count = _blocks(vecs, code, owner, n, params.cells)
    if document:
        if params.doc_block == "mean":
            # A filled cell holds one vector; the divisor is never below 1.
            divisor = np.maximum(1, count)[:, :, None]
            total = np.floor(total / divisor).astype(np.int64) if params.arithmetic == "fixed" else total / divisor.astype(np.float32)
        if params.fill:
            _fill(total, count, vecs, code, owner, params, centers)
    return total


def _encode(vecs: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams, centers: np.ndarray | None, document: bool) -> np.ndarray:
    fixed = params.arithmetic == "fixed"
    codes = cells_of(vecs, params, centers)
    signs = seeds.inner_signs(params.seed, params.reps, params.proj_dim, params.dim, params.plane_law) if params.projected else None
    out = np.zeros((n, params.width), number_type(params))
    span = params.cells * params.proj_dim
    for rep in range(params.reps):
        total = rep_blocks(vecs, codes[:, rep], owner, n, params, None if centers is None else centers[rep], document)
        if signs is not None:
            total = total @ signs[rep].T
            if not fixed:
                total /= np.float32(np.sqrt(params.proj_dim))
        flat = total.reshape(n, span)
        if params.final_dim is None:
            out[:, rep * span : (rep + 1) * span] = flat
        else:
            part = flat @ seeds.final_signs(params.seed, rep, span, params.final_dim, params.plane_law)
            out += part if fixed else part / np.float32(np.sqrt(params.final_dim))
    return out


def _cell_sums(points: np.ndarray, which: np.ndarray, at: np.ndarray, firsts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Sums of the points of each run ``at[firsts[i] : firsts[i] + sizes[i]]``; runs come by falling size. All runs' first
    points are taken, then all second ones are added, and so on, as most runs are short; the rest of long ones at once."""
    taken = which[at]
    total = points.take(taken[firsts], axis=0)
    live = np.searchsorted(-sizes, -np.arange(1, min(LONG, sizes[0]) + 1), side="left") if len(sizes) else np.zeros(0, int)
    for r, k in enumerate(live[: LONG - 1].tolist(), 1):
        total[:k] += points.take(taken[firsts[:k] + r], axis=0)
    for i in np.flatnonzero(sizes > LONG).tolist():
        total[i] += points[taken[firsts[i] + LONG : firsts[i] + sizes[i]]].sum(0)
    return total


def _put_blocks(out: np.ndarray, at_row: int, stride: int, n: int, points: np.ndarray, code: np.ndarray, which: np.ndarray, base: np.ndarray, params: EncodeParams, document: bool) -> None:
    """Projected blocks of one repetition, as of ``rep_blocks``, into the rows of ``out`` (blocks, proj), which holds zeros: a
    bag's begin at ``at_row``, those of the next bag ``stride`` below. ``points`` and ``code`` are those of distinct vectors,
    ``which`` of them each vector is, ``base`` its bag's first cell."""
    cells = params.cells
    flat = base + code.astype(base.dtype)[which]
    order = np.argsort(flat, kind="stable")
    at = flat[order]
    firsts = np.flatnonzero(np.concatenate([[True], at[1:] != at[:-1]])[: len(at)])
    sizes = np.diff(firsts, append=len(at))
    # Beyond the two bytes that sort fast the order of long runs does not matter.
    falling = np.argsort((65535 - np.minimum(sizes, 65535)).astype(np.uint16), kind="stable")
    firsts, sizes = firsts[falling], sizes[falling]
    total = _cell_sums(points, which, order, firsts, sizes)
    if document and params.doc_block == "mean":
        total /= sizes[:, None].astype(np.float32)
    cell = at[firsts].astype(np.int64)
    out[at_row + cell // cells * stride + cell % cells] = total
    if document and params.fill:
        none = len(which)
        first = np.full(n * cells, none, np.int32)
        first[cell] = order[firsts]
        first = first.reshape(n, cells)
        bag, hole = np.nonzero((first == none) & (first.min(1) < none)[:, None])
        if not len(bag):
            return
        # The smallest place among codes that differ in one bit, which most empty cells have, then in two, and so on.
        taken, left = np.full(len(bag), none, np.int32), np.arange(len(bag))
        for codes in _by_distance(cells):
            near = hole[left][:, None] ^ codes
            own = np.where(near < cells, first[bag[left][:, None], np.minimum(near, cells - 1)], none) if cells & (cells - 1) else first[bag[left][:, None], near]
            taken[left] = own.min(1)
            left = left[taken[left] == none]
            if not len(left):
                break
        out[at_row + bag * stride + hole] = points.take(which[taken], axis=0)


def map_points(vecs: np.ndarray, params: EncodeParams) -> tuple[np.ndarray, np.ndarray]:
    """Cells (reps, vectors) and mapped vectors (reps, vectors, proj) in floats, for a partition without centres. Maps inside
    blocks are linear, so distinct vectors are mapped once for all repetitions, and sums are of the mapped, shorter ones."""
    codes = np.ascontiguousarray(cells_of(vecs, params).T)
    if not params.projected:
        return codes, np.broadcast_to(vecs, (params.reps, *vecs.shape))
    signs = seeds.inner_signs(params.seed, params.reps, params.proj_dim, params.dim, params.plane_law).astype(np.float32)
    return codes, vecs @ (signs / np.float32(np.sqrt(params.proj_dim))).transpose(0, 2, 1)


def encode_mapped(codes: np.ndarray, points: np.ndarray, which: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams, side: str) -> np.ndarray:
    """Encodings of bags 0..n-1 whose vectors are those of ``map_points`` at ``which``."""
    document = side == "document"
    base = (owner * params.cells).astype(np.uint16 if n * params.cells <= 1 << 16 else np.int64)
    out = np.zeros((n, params.width), np.float32)
    for rep in range(params.reps):
        if params.final_dim is None:
            _put_blocks(out.reshape(-1, params.proj_dim), rep * params.cells, params.reps * params.cells, n, points[rep], codes[rep], which, base, params, document)
            continue
        own = np.zeros((n * params.cells, params.proj_dim), np.float32)
        _put_blocks(own, 0, params.cells, n, points[rep], codes[rep], which, base, params, document)
        span = params.cells * params.proj_dim
        out += own.reshape(n, span) @ seeds.final_signs(params.seed, rep, span, params.final_dim, params.plane_law) / np.float32(np.sqrt(params.final_dim))
    return out


def scored(encoded: np.ndarray, vecs: np.ndarray, which: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams) -> np.ndarray:
    """Products (queries, n) of encoded queries with the documents' encodings of bags 0..n-1, whose vectors are
    ``vecs[which]``. A repetition of ``AT_ONCE`` bags is held at a time, so blocks are made and multiplied within a core's
    cache and no encoding is ever whole."""
    if params.final_dim is not None:
        return encoded @ encode_distinct(vecs, which, owner, n, params, "document").T
    out, span = np.zeros((len(encoded), n), np.float32), params.cells * params.proj_dim
    codes = np.ascontiguousarray(cells_of(vecs, params).T)
    signs = seeds.inner_signs(params.seed, params.reps, params.proj_dim, params.dim, params.plane_law).astype(np.float32) / np.float32(np.sqrt(params.proj_dim)) if params.projected else None
    points, own = np.empty((len(vecs), params.proj_dim), np.float32), np.empty((AT_ONCE * params.cells, params.proj_dim), np.float32)
    starts = np.searchsorted(owner, np.arange(0, n + AT_ONCE, AT_ONCE))
    base = (owner % AT_ONCE * params.cells).astype(np.uint16 if AT_ONCE * params.cells <= 1 << 16 else np.int64)
    for rep in range(params.reps):
        points = vecs if signs is None else np.matmul(vecs, signs[rep].T, out=points)
        asked = encoded[:, rep * span : (rep + 1) * span]
        for at, a in enumerate(range(0, n, AT_ONCE)):
            m, part = min(AT_ONCE, n - a), slice(starts[at], starts[at + 1])
            own[:] = 0
            _put_blocks(own, 0, params.cells, m, points, codes[rep], which[part], base[part], params, True)
            out[:, a : a + m] += asked @ own[: m * params.cells].reshape(m, span).T
    return out


def encode(vecs: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams, side: str, centers: np.ndarray | None = None) -> np.ndarray:
    """Encodings (n, width) of bags 0..n-1. ``side='query'``: blocks are sums and never filled; ``side='document'``:
    blocks are means (or sums, as an ablation) and empty cells are filled if ``params.fill``."""
    if side not in ("query", "document"):
        raise ValueError("side is query or document")
    if params.arithmetic == "float":
        # Whole-number vectors meet planes of fractions as floats of their own scale.
        vecs = vecs.astype(np.float32, copy=False)
    if params.arithmetic == "float" and params.partition != "center":
        return encode_distinct(vecs, np.arange(len(vecs)), owner, n, params, side)
    step = max(1, SLICE // (params.cells * params.dim))
    parts = []
    for a in range(0, n, step):
        lo, hi = np.searchsorted(owner, [a, a + step])
        parts.append(_encode(vecs[lo:hi], owner[lo:hi] - a, min(step, n - a), params, centers, side == "document"))
    return np.concatenate(parts) if parts else np.zeros((0, params.width), number_type(params))


def encode_distinct(distinct: np.ndarray, which: np.ndarray, owner: np.ndarray, n: int, params: EncodeParams, side: str) -> np.ndarray:
    """``encode`` in floats of bags whose vectors are ``distinct[which]``: what repeats between bags is mapped once a slice."""
    step = max(1, SLICE // (16 * params.cells * params.dim))
    parts = []
    for a in range(0, n, step):
        lo, hi = np.searchsorted(owner, [a, a + step])
        used, own = np.unique(which[lo:hi], return_inverse=True)
        parts.append(encode_mapped(*map_points(distinct[used], params), own, owner[lo:hi] - a, min(step, n - a), params, side))
    return np.concatenate(parts) if parts else np.zeros((0, params.width), np.float32)


PARTITIONS["axis"] = axis_cells


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """``a @ b.T``. Whole numbers go by doubles where these hold every partial sum exactly (it is at most the product of two
    lengths), which is many times as fast; else by whole numbers."""
    if a.dtype.kind == "i" and a.size and b.size:
        x, y = a.astype(np.float64), b.astype(np.float64)
        length = lambda z: np.sqrt(np.einsum("nd,nd->n", z, z).max())
        if length(x) * length(y) < 1 << 52:
            return (x @ y.T).astype(np.int64)
    return a @ b.T


def maxsim_table(queries: np.ndarray, owner: np.ndarray, n: int, vecs: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """MaxSim (n, documents) of stacked query bags 0..n-1 with stacked documents, by tiles of at most about ``TILE`` products.
    A query without vectors scores 0."""
    out = np.zeros((n, len(starts)), vecs.dtype)
    firsts = np.flatnonzero(np.diff(owner, prepend=-1))
    ends = np.append(firsts, len(owner))
    a = 0
    while a < len(firsts):
        b = max(a + 1, int(np.searchsorted(ends, ends[a] + max(1, TILE // max(1, len(vecs))), side="right")) - 1)
        best = np.maximum.reduceat(products(queries[ends[a] : ends[b]], vecs), starts, axis=1)
        out[owner[firsts[a:b]]] = np.add.reduceat(best, firsts[a:b] - firsts[a], axis=0)
        a = b
    return out


class Hits:
    """The ``k`` best document vectors of each query vector so far, ties to the smaller document and then place: arrays of
    (query vector, document, place, score), ordered by query vector."""

    def __init__(self, n: int, k: int, number: type):
        self.n, self.k = n, k
        self.rows, self.ids, self.places = (np.zeros(0, np.int64) for _ in range(3))
        self.scores = np.zeros(0, number)

    def add(self, queries: np.ndarray, vecs: np.ndarray, ids: np.ndarray, places: np.ndarray) -> None:
        """Scores by tiles of at most about ``TILE`` products, of which those below a query vector's k-th best are left out."""
        step = max(1, TILE // max(1, len(vecs)))
        parts: list[tuple[np.ndarray, ...]] = []
        for a in range(0, self.n, step):
            lo, hi = np.searchsorted(self.rows, [a, a + step])
            held = tuple(x[lo:hi] for x in (self.rows, self.ids, self.places, self.scores))
            score = products(queries[a : a + step], vecs)
            count = np.bincount(held[0] - a, minlength=len(score))
            full = count == self.k
            if len(vecs) > 4 * self.k:
                floor = np.full(len(score), score.min(), score.dtype)
                floor[held[0][np.cumsum(count)[full] - 1] - a] = held[3][np.cumsum(count)[full] - 1]
                if not full.all():
                    floor[~full] = np.partition(score[~full], -self.k, axis=1)[:, -self.k]
                row, at = np.nonzero(score >= floor[:, None])
            else:
                row, at = (x.ravel() for x in np.indices(score.shape))
            row, doc, place, s = (np.concatenate([x, y]) for x, y in zip(held, (row + a, ids[at], places[at], score[row, at]), strict=True))
            order = np.lexsort((place, doc, -s, row))
            row = row[order]
            first = np.arange(len(row)) - np.searchsorted(row, row) < self.k
            parts.append((row[first], *(x[order][first] for x in (doc, place, s))))
        if parts:
            self.rows, self.ids, self.places, self.scores = (np.concatenate(x) for x in zip(*parts, strict=True))


def maxsim(query: np.ndarray, vecs: np.ndarray, starts: np.ndarray, kind: str = "dot") -> np.ndarray:
    """MaxSim of one query bag with every document bag that isn't empty (``starts`` holds their first rows). The
    ``distance`` kind sums each query vector's least squared distance instead."""
    product = vecs @ query.T
    if kind == "distance":
        far = (vecs * vecs).sum(1)[:, None] - 2 * product + (query * query).sum(1)
        return np.minimum.reduceat(far, starts, axis=0).sum(1)
    return np.maximum.reduceat(product, starts, axis=0).sum(1)


def best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of the ``k`` highest scores, ties to the smaller id."""
    if len(ids) > 4 * k:
        floor = np.partition(scores, -k)[-k]
        near = np.flatnonzero(scores >= floor)
    else:
        near = np.arange(len(ids))
    return near[np.lexsort((ids[near], -scores[near]))[:k]]


def carve(query: np.ndarray, tau: float) -> tuple[np.ndarray, np.ndarray]:
    """Greedy groups of a query's vectors: in order, a free vector is a seed and takes all free vectors whose product
    with it is at least ``tau``. Returns the groups' sums and each vector's group."""
    product = query @ query.T
    group = np.full(len(query), -1)
    n = 0
    for i in range(len(query)):
        if group[i] < 0:
            group[(group < 0) & (product[i] >= tau)] = n
            group[i] = n
            n += 1
    sums = np.zeros((n, query.shape[1]), query.dtype)
    np.add.at(sums, group, query)
    return sums, group


def lloyd(points: np.ndarray, start: np.ndarray, rounds: int, weight: np.ndarray | None = None) -> np.ndarray:
    """Fixed rounds of k-means; an empty centre keeps its place, a tie goes to the lower number."""
    centers = start.astype(np.float64).copy()
    weight = np.ones(len(points)) if weight is None else weight
    for _ in range(rounds):
        # A slice of rows and its scores stay in a core's cache.
        code = np.concatenate([nearest_center(points[a : a + AT_ONCE], centers) for a in range(0, len(points), AT_ONCE)])
        mass = np.bincount(code, weight, len(centers))
        total = np.stack([np.bincount(code, weight * points[:, d], len(centers)) for d in range(points.shape[1])], 1)
        centers[mass > 0] = total[mass > 0] / mass[mass > 0][:, None]
    return centers.astype(np.float32)
