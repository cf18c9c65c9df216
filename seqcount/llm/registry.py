"""Queries and SQL of the training-data operators, for the driver's entry module."""

from seqcount.llm import bpe, exact_dedup, mixing, quality_knn, sharding, simhash, token_counts, topk_nra, toxicity_ftrl, warc

QUERIES = {
    "op1_exact_dedup": exact_dedup.op1_exact_dedup,
    "op2_quality": quality_knn.op2_quality,
    "op3_sharding": sharding.op3_sharding,
    "op4_topk": topk_nra.op4_topk,
    "op5_toxicity": toxicity_ftrl.op5_toxicity,
    "op6_warc": warc.op6_warc,
    "op7_bpe": bpe.op7_bpe,
    "op8_token_counts": token_counts.op8_token_counts,
    "op9_simhash": simhash.op9_simhash,
    "op10_mixing": mixing.op10_mixing,
}
SQL = {
    "op1_exact_dedup": exact_dedup.OP1_SQL, "op4_topk": topk_nra.OP4_SQL, "op6_warc": warc.OP6_SQL, "op10_mixing": mixing.OP10_SQL,
}
