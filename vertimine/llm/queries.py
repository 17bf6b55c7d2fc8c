"""The queries of this subpackage, and DuckDB SQL where SQL can express them."""

from pyspark.sql import functions as F

from . import bm25, bpe, exact_dedup, language, licenses, mixing, quotes, simhash, token_files, toxicity

QUERIES = {
    "op1_quote_links": quotes.op1_quote_links,
    "op2_license_diagonals": licenses.op2_license_diagonals,
    "op3_exact_dedup": exact_dedup.op3_exact_dedup,
    "op4_bm25_documents": lambda spark, sf_dir: bm25.op4_bm25_documents(spark, sf_dir).withColumn("score", F.round("score", 5)),
    "op5_bpe_prefix_dp": bpe.op5_bpe_prefix_dp,
    "op6_toxicity_ftrl": toxicity.op6_toxicity_ftrl,
    "op7_mix_pivotal": mixing.op7_mix_pivotal,
    "op8_token_files": token_files.op8_token_files,
    "op9_simhash_gray": simhash.op9_simhash_gray,
    "op10_language_mixture": language.op10_language_mixture,
}
SQL = {"op3_exact_dedup": exact_dedup.OP3_SQL, "op4_bm25_documents": bm25.OP4_SQL}
