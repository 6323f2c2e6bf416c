"""The queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from annspark.llm import chat_format, maxscore, token_counts
from annspark.llm.cross_polytope import op10_cross_polytope
from annspark.llm.language_id import op2_language_id
from annspark.llm.maxscore import op9_maxscore_top_k
from annspark.llm.mixing import op7_mix_sources
from annspark.llm.pii import op4_contextual_pii
from annspark.llm.secrets import op3_secret_scan
from annspark.llm.sentencepiece_codec import op8_sentencepiece_codec
from annspark.llm.simhash import op6_simhash_near_dedup

QUERIES = {
    "op1_token_counts": token_counts.op1_token_counts,
    "op2_language_id": op2_language_id,
    "op3_secret_scan": op3_secret_scan,
    "op4_contextual_pii": op4_contextual_pii,
    "op5_chat_format": chat_format.op5_chat_format,
    "op6_simhash_near_dedup": op6_simhash_near_dedup,
    "op7_mix_sources": op7_mix_sources,
    "op8_sentencepiece_codec": op8_sentencepiece_codec,
    "op9_maxscore_top_k": op9_maxscore_top_k,
    "op10_cross_polytope": op10_cross_polytope,
    "token_rollup_words": token_counts.token_rollup_words,
}

ORACLES: dict[str, str] = {"op5_chat_format": chat_format.ORACLE, "op9_maxscore_top_k": maxscore.ORACLE, "token_rollup_words": token_counts.ORACLE_WORDS}
