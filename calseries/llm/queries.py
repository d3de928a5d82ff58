"""The registered queries of this subpackage and, where SQL can say the same, their DuckDB text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .chat import OP1_SQL, op1_chat_format
from .gru_lm import op10_gru_lm
from .jaccard_join import op7_heavy_light_join
from .jpeg import op6_jpeg
from .language import op8_mixture_language
from .line_rules import op5_line_rules
from .mixing import OP4_SQL, op4_source_mix
from .packing import op3_pattern_packing
from .quality import op9_random_indexing
from .toxicity import op2_factorization_machine


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "pipeline": pipeline,
    "op1_chat_format": op1_chat_format,
    "op2_factorization_machine": op2_factorization_machine,
    "op3_pattern_packing": op3_pattern_packing,
    "op4_source_mix": op4_source_mix,
    "op5_line_rules": op5_line_rules,
    "op6_jpeg": op6_jpeg,
    "op7_heavy_light_join": op7_heavy_light_join,
    "op8_mixture_language": op8_mixture_language,
    "op9_random_indexing": op9_random_indexing,
    "op10_gru_lm": op10_gru_lm,
}
ORACLES = {"op1_chat_format": OP1_SQL, "op4_source_mix": OP4_SQL}
