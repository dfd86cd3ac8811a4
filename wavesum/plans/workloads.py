"""The experiments by name: which registered queries show which published curve."""

from __future__ import annotations

#: Workload: what varies, and its queries.
WORKLOADS: dict[str, tuple[str, list[str]]] = {
    "k": ("number of coefficients", ["sweep_k_methods_words", "sweep_k_methods_value", "sweep_k_sse_partkey", "sweep_k_sse_words", "sweep_k_sketch_user"]),
    "eps": ("sampling error", ["sweep_eps_methods_words", "sweep_eps_methods_user", "sweep_eps_sse"]),
    "cost_at_error": ("eps and sketch size", ["cost_at_error_words", "cost_at_error_user", "cost_at_error_log_user_type", "cost_vs_sse", "sweep_sketch_user"]),
    "records": ("n, with sites of one size", ["sweep_n_methods", "sweep_n_comm"]),
    "record_size": ("bytes of a record", ["sweep_record_size", "two_stage_hist_seek_fixed", "seek_sample_fixed"]),
    "domain": ("size of the key domain", ["sweep_u_methods", "sweep_u_comm"]),
    "splits": ("number of sites", ["sweep_m_methods", "sweep_m_comm"]),
    "skew": ("Zipf exponent", ["sweep_skew_methods", "sweep_skew_comm", "sweep_skew_sketch"]),
    "bandwidth": ("share of the link", ["bandwidth_methods", "bandwidth_model"]),
    "composite_key": ("composite keys of a log", ["log_methods_user_type", "log_eps_user_type", "log_methods_pair", "ship_counts_pair", "signed_topk_pair"]),
    "dimensions": ("keys of two and three dimensions", ["ship_counts_2d", "signed_topk_2d", "two_stage_2d", "coarsen_2d", "ship_counts_3d", "signed_topk_3d"]),
    "order": ("contiguous or mixed sites", ["sweep_order_methods", "signed_topk_user_mixed", "signed_topk_contiguous_events"]),
    "ablations": ("resending, bounds, designs, updates", ["ablation_resend_tight", "uniform_coin_events", "uniform_wor_events", "uniform_precombine_events", "sketch_cells_keywise_user"]),
    "rounds": ("what each round sends", ["signed_topk_phases_words", "rounds_value", "rounds_partkey"]),
    "seconds": ("wall time of every method", ["times_partkey", "times_price", "times_value", "times_zipf", "sweep_n_times", "sweep_m_times"]),
    "signed_scores": ("top-k of scores of any sign", ["topk_signed_embeddings"]),
}


def figures(name: str, spark, sf_dir: str) -> dict:
    """The rows of a workload's queries, each run once: what the published curve shows, here."""
    return {q: df.collect() for q, df in run(name, spark, sf_dir).items()}


def run(name: str, spark, sf_dir: str) -> dict:
    """The DataFrames of a workload by query name."""
    from wavesum.queries import queries

    every = queries()
    return {q: every[q](spark, sf_dir) for q in WORKLOADS[name][1]}
