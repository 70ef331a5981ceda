"""The document operators' queries and their DuckDB statements."""

from __future__ import annotations

from exactrank.llm.language_model import op2_elias_fano_lm
from exactrank.llm.licenses import OP7_SQL, op7_license_scan
from exactrank.llm.lsh_forest import OP4_SQL, op4_lsh_forest_join
from exactrank.llm.packing import op5_complement_packing
from exactrank.llm.quality import op6_quality_rules
from exactrank.llm.repeats import op10_suffix_dedup
from exactrank.llm.sentence_pieces import op8_sentence_pieces
from exactrank.llm.sharding import OP3_SQL, op3_rendezvous_shards
from exactrank.llm.syncmers import op1_syncmer_fingerprints
from exactrank.llm.unigram_counts import op9_unigram_token_counts

_QUERIES = [op1_syncmer_fingerprints, op2_elias_fano_lm, op3_rendezvous_shards, op4_lsh_forest_join, op5_complement_packing, op6_quality_rules, op7_license_scan, op8_sentence_pieces, op9_unigram_token_counts, op10_suffix_dedup]


def queries() -> dict:
    return {q.__name__: q for q in _QUERIES}


def oracle_sql() -> dict[str, str]:
    return {"op3_rendezvous_shards": OP3_SQL, "op4_lsh_forest_join": OP4_SQL, "op7_license_scan": OP7_SQL}
