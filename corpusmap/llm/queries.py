"""The registered queries of this subpackage."""

from __future__ import annotations

from corpusmap.llm.embedding_neardup import OP10_SQL, op10_epsilon_grid_neardup
from corpusmap.llm.exact_dedup import OP5_SQL, op5_streaming_exact_dedup
from corpusmap.llm.hmm_lm import op1_hmm_language_model
from corpusmap.llm.mixing import op3_hypergeometric_mixing
from corpusmap.llm.packing import op4_best_fit_packing
from corpusmap.llm.quality_mil import op6_attention_mil_quality
from corpusmap.llm.sharding import op9_histogram_sharding
from corpusmap.llm.simhash_neardup import op7_simhash_neardup
from corpusmap.llm.substring_dedup import OP2_SQL, op2_debruijn_substring_dedup
from corpusmap.llm.toxicity import op8_counterfactual_toxicity


def queries() -> dict:
    import corpus_pipeline

    ops = (op1_hmm_language_model, op2_debruijn_substring_dedup, op3_hypergeometric_mixing, op4_best_fit_packing, op5_streaming_exact_dedup,
           op6_attention_mil_quality, op7_simhash_neardup, op8_counterfactual_toxicity, op9_histogram_sharding, op10_epsilon_grid_neardup)
    return {f.__name__: f for f in ops} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    import corpus_pipeline

    found = {"op2_debruijn_substring_dedup": OP2_SQL, "op5_streaming_exact_dedup": OP5_SQL, "op10_epsilon_grid_neardup": OP10_SQL}
    return found | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
