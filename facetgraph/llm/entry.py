"""Queries of this subpackage and their SQL, for ``__spark_entry__.py``."""

from __future__ import annotations

from facetgraph.llm.decontaminate import op8_decontaminate
from facetgraph.llm.licenses import op7_license_scan
from facetgraph.llm.lm_score import op10_lm_score
from facetgraph.llm.mixing import OP2_SQL, op2_mix_sources
from facetgraph.llm.ngram_join import op9_ngram_jaccard
from facetgraph.llm.oracles import OP8_SQL, OP9_SQL, op7_sql, op10_sql
from facetgraph.llm.quality import op6_quality
from facetgraph.llm.sharding import op3_shard_documents
from facetgraph.llm.substring_dedup import op1_shared_passages
from facetgraph.llm.syncmers import op5_syncmer_fingerprints
from facetgraph.llm.toxicity import op4_toxicity

QUERIES = {
    "op1_shared_passages": op1_shared_passages,
    "op2_mix_sources": op2_mix_sources,
    "op3_shard_documents": op3_shard_documents,
    "op4_toxicity": op4_toxicity,
    "op5_syncmer_fingerprints": op5_syncmer_fingerprints,
    "op6_quality": op6_quality,
    "op7_license_scan": op7_license_scan,
    "op8_decontaminate": op8_decontaminate,
    "op9_ngram_jaccard": op9_ngram_jaccard,
    "op10_lm_score": op10_lm_score,
}

ORACLES: dict[str, str] = {
    "op2_mix_sources": OP2_SQL,
    "op7_license_scan": op7_sql(),
    "op8_decontaminate": OP8_SQL,
    "op9_ngram_jaccard": OP9_SQL,
    "op10_lm_score": op10_sql(),
}
