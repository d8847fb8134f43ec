"""Registered queries of the training-data operators."""

from __future__ import annotations

from vecengine.llm.chat import op8_chat_quotes
from vecengine.llm.embedding_dedup import op10_embedding_near_dedup
from vecengine.llm.fingerprints import op9_closed_syncmers
from vecengine.llm.html_extract import op1_extract_html
from vecengine.llm.mixing import MIX_SQL, op5_mix_sources
from vecengine.llm.near_dedup import op6_minhash_near_dedup
from vecengine.llm.pieces import op2_sentencepiece
from vecengine.llm.sharding import SHARDS_SQL, op4_sharding
from vecengine.llm.toxicity import op3_toxicity
from vecengine.llm.warc import op7_warc

QUERIES = {
    "op1_extract_html": op1_extract_html,
    "op2_sentencepiece": op2_sentencepiece,
    "op3_toxicity": op3_toxicity,
    "op4_sharding": op4_sharding,
    "op5_mix_sources": op5_mix_sources,
    "op6_minhash_near_dedup": op6_minhash_near_dedup,
    "op7_warc": op7_warc,
    "op8_chat_quotes": op8_chat_quotes,
    "op9_closed_syncmers": op9_closed_syncmers,
    "op10_embedding_near_dedup": op10_embedding_near_dedup,
}
ORACLES: dict[str, str] = {
    "op4_sharding": SHARDS_SQL,
    "op5_mix_sources": MIX_SQL,
}
