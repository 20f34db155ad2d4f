"""Queries of the training-data operators, and SQL for those that it expresses."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from crowding.llm import jaccard_join, poisson_mix, token_counts, warc
from crowding.llm.bpe_automaton import op10_bpe_automaton
from crowding.llm.elias_fano import op8_elias_fano
from crowding.llm.maxent_lm import op5_maxent_lm
from crowding.llm.media import op2_media_columns
from crowding.llm.simhash import op3_simhash
from crowding.llm.toxicity import op4_toxicity


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = [
        token_counts.op1_token_counts, op2_media_columns, op3_simhash, op4_toxicity, op5_maxent_lm, warc.op6_warc_revisits,
        jaccard_join.op7_jaccard_join, op8_elias_fano, poisson_mix.op9_poisson_mix, op10_bpe_automaton,
    ]
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    return {"op1_token_counts": token_counts.SQL, "op6_warc_revisits": warc.SQL, "op7_jaccard_join": jaccard_join.SQL, "op9_poisson_mix": poisson_mix.SQL}
