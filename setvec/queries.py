"""Queries over the given tables by name, and the SQL that each is compared with."""

from setvec import experiments, oracle, workloads

#: Sweeps that take a minute and more on a small table, from the shortest to the longest.
LONG = (
    "final_map_gain", "text_grid_recall", "text_grid_frontier", "carve_throughput", "carve_sweep", "text_candidates", "code_schemes", "latency_bars", "throughput",
    "evaluated_way", "text_partition_grid", "vector_candidates", "graph_code_sweep", "text_candidates_wide", "compared_over_corpora", "comparison_ratios",
)
QUERIES = {name: run for name, run in (workloads.QUERIES | experiments.QUERIES).items() if name not in LONG}
QUERIES |= {name: experiments.QUERIES[name] for name in LONG}
SQL = {name: text for name, text in oracle.SQL.items() if name in QUERIES}
flagship = workloads.flagship
