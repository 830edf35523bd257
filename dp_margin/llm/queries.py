"""Registered queries of the training-data operators and their SQL, where SQL can express them."""

from __future__ import annotations

from . import decontam, language, linededup, neardup, pieces, secrets, telephony, tokenfiles, wrappers

QUERIES = {"op9_html_wrappers": wrappers.op9_html_wrappers, "page_wrappers": wrappers.page_wrappers, "op2_sentencepiece": pieces.op2_sentencepiece, "op6_language_id": language.op6_language_id, "lang_id_pages": language.lang_id_pages, "op1_telephony_audio": telephony.op1_telephony_audio, "op4_secret_scan": secrets.op4_secret_scan, "op5_line_dedup": linededup.op5_line_dedup, "op7_minhash_near_dup": neardup.op7_minhash_near_dup, "op8_spaced_seed_decontam": decontam.op8_spaced_seed_decontam, "op3_separator_scan": tokenfiles.op3_separator_scan, "op10_arrow_token_files": tokenfiles.op10_arrow_token_files}
ORACLES = {"op5_line_dedup": linededup.ORACLE, "op8_spaced_seed_decontam": decontam.ORACLE}
