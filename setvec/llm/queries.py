"""The operators' queries by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from setvec.llm import idfile, language, licences, media, mixing, near, packing, quality, secrets, topk

QUERIES = {
    "op1_media_columns": media.op1_media_columns,
    "op2_impact_topk": topk.op2_impact_topk,
    "op3_secret_ledger": secrets.op3_secret_ledger,
    "op4_ngram_jaccard": near.op4_ngram_jaccard,
    "op5_source_mix": mixing.op5_source_mix,
    "op6_naive_bayes_svm": quality.op6_naive_bayes_svm,
    "op7_huffman_ids": idfile.op7_huffman_ids,
    "op8_rare_token_licences": licences.op8_rare_token_licences,
    "op9_shortest_pack": packing.op9_shortest_pack,
    "op10_language_mixture": language.op10_language_mixture,
}
SQL = {"op2_impact_topk": topk.OP2_SQL, "op5_source_mix": mixing.OP5_SQL}
