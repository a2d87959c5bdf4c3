"""Registered queries of this subpackage and their SQL."""

from __future__ import annotations

from localfreq.llm.bpe import op5_bpe_round_trip
from localfreq.llm.bradleyterry import op1_quality_scores
from localfreq.llm.fingerprint import op4_document_fingerprints
from localfreq.llm.packing import op3_best_fit_packing
from localfreq.llm.secrets import op10_secret_scans
from localfreq.llm.simjoin import op2_ngram_jaccard_join
from localfreq.llm.tokencount import op9_token_counts
from localfreq.llm.topk import op7_exact_topk
from localfreq.llm.toxicity import op6_toxicity
from localfreq.llm.urlfilter import op8_url_filters

QUERIES = {f.__name__: f for f in (op1_quality_scores, op2_ngram_jaccard_join, op3_best_fit_packing, op4_document_fingerprints, op5_bpe_round_trip, op6_toxicity, op7_exact_topk, op8_url_filters, op9_token_counts, op10_secret_scans)}

ORACLES: dict[str, str] = {}
