"""The queries of this subpackage and the SQL that expresses them."""

from __future__ import annotations

from edgefold.llm import chat, embedding_dedup, language_id, mixing, packing, simhash, suffix_dedup, token_files, toxicity, weighted_sampling

QUERIES = {
    "op1_simhash": simhash.op1_simhash,
    "op2_packing": packing.op2_packing,
    "op3_suffix_array": suffix_dedup.op3_suffix_array,
    "op4_fingerprints": weighted_sampling.op4_fingerprints,
    "op5_mixing": mixing.op5_mixing,
    "op6_language_id": language_id.op6_language_id,
    "op7_token_files": token_files.op7_token_files,
    "op8_embeddings": embedding_dedup.op8_embeddings,
    "op9_toxicity": toxicity.op9_toxicity,
    "op10_chat": chat.op10_chat,
}
ORACLE: dict[str, str] = {"op10_chat": chat.OP10_SQL}
