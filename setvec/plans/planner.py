"""Which way to run a retrieval: decided from settings and sizes while the logical plan is built."""

from __future__ import annotations

from dataclasses import dataclass

from setvec.plans.params import EncodeParams

#: Numbers that one task may scan for a query before an index pays, and bytes of dense encodings worth keeping.
SCAN_NUMBERS = 10**12
DENSE_BYTES = 10**12
RELATIONAL_ROWS = 10**8


@dataclass(frozen=True)
class Choice:
    index: str
    encoder: str
    project: str
    rerank: str
    first_reps: int
    reasons: tuple[str, ...]

    def explain(self) -> str:
        head = f"index={self.index} encoder={self.encoder} project={self.project} rerank={self.rerank} first_reps={self.first_reps}"
        return "\n".join([head, *(f"  - {r}" for r in self.reasons)])


def choose(params: EncodeParams, n_docs: int, m_avg: float, n_queries: int, query_vectors: int = 32, interactive: bool = False) -> Choice:
    """Dense, sparse, coded, inverted or graph search; packed or relational encoding; vectors or blocks projected first;
    candidates of a query together or spread; and how many repetitions a first pass scores."""
    reasons = []
    numbers = n_docs * params.width
    occupied = 1 - (1 - 1 / params.cells) ** query_vectors
    if interactive and numbers > SCAN_NUMBERS:
        index = "graph"
        reasons.append(f"one query at a time over {numbers:.2g} numbers: walk a graph, shards routed by their centres")
    elif numbers > SCAN_NUMBERS and n_queries < 1000:
        index = "ivf"
        reasons.append(f"{n_queries} queries don't pay for a scan of {numbers:.2g} numbers: probe lists")
    elif 4 * numbers > DENSE_BYTES:
        index = "pq"
        reasons.append(f"{4 * numbers:.2g} bytes of dense encodings: scan codes, 32 times fewer")
    elif params.final_dim is None and occupied < 0.4:
        index = "sparse"
        reasons.append(f"a query occupies {occupied:.0%} of the blocks: skip the rest")
    else:
        index = "dense"
        reasons.append("a scan of whole encodings" + (": the last map leaves no empty block" if params.final_dim else ""))
    rows = n_docs * m_avg * params.reps * params.dim
    encoder = "relational" if params.arithmetic == "fixed" and rows <= RELATIONAL_ROWS else "packed"
    reasons.append(f"the relational encoder would make {rows:.2g} rows")
    project = "vectors" if m_avg < params.cells else "blocks"
    reasons.append(f"{m_avg:.0f} vectors against {params.cells} blocks a document: project the fewer")
    mode = "spread" if n_queries < 64 else "per_query"
    reasons.append(f"{n_queries} queries: candidates {'of a query over tasks' if mode == 'spread' else 'of a query in one task'}")
    first = max(1, params.reps // 4) if index in ("dense", "sparse") and params.final_dim is None and params.reps >= 8 else params.reps
    if first < params.reps:
        reasons.append(f"the first {first} repetitions are a narrower encoding of their own: score them first")
    return Choice(index, encoder, project, mode, first, tuple(reasons))
