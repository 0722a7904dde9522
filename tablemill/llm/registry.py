"""Queries of the training-data operators and their oracles."""

from tablemill.llm import bpe, language, licenses, line_dedup, raking, rans, scaled_sketch, simhash, telephony, wordpiece

QUERIES = {
    "op1_line_dedup": line_dedup.op1_line_dedup,
    "op2_scaled_sketch": scaled_sketch.op2_scaled_sketch,
    "op3_license_scan": licenses.op3_license_scan,
    "op4_telephony_media": telephony.op4_telephony_media,
    "op5_wordpiece_counts": wordpiece.op5_wordpiece_counts,
    "op6_language_id": language.op6_language_id,
    "op7_rans_token_ids": rans.op7_rans_token_ids,
    "op8_simhash_near_dedup": simhash.op8_simhash_near_dedup,
    "op9_raked_mix": raking.op9_raked_mix,
    "op10_duckdb_bpe": bpe.op10_duckdb_bpe,
}

ORACLES = {
    "op1_line_dedup": line_dedup.OP1_SQL,
    "op9_raked_mix": raking.op9_sql(),
}
