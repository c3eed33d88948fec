"""Queries of this subpackage and, where SQL can express them, their DuckDB twins."""

from __future__ import annotations

from detspark.llm import licences
from detspark.llm.lines import op3_line_dedup
from detspark.llm.mixture import op9_mixture
from detspark.llm.multiindex import op4_multiindex
from detspark.llm.packing import op7_packing
from detspark.llm.quality import op1_quality
from detspark.llm.shards import op5_shards
from detspark.llm.simhash import op10_simhash
from detspark.llm.topk import op6_topk
from detspark.llm.warc import op2_warc


def pipeline(spark, sf_dir: str):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {
    "op1_quality": op1_quality,
    "op2_warc": op2_warc,
    "op3_line_dedup": op3_line_dedup,
    "op4_multiindex": op4_multiindex,
    "op5_shards": op5_shards,
    "op6_topk": op6_topk,
    "op7_packing": op7_packing,
    "op8_licences": licences.op8_licences,
    "op9_mixture": op9_mixture,
    "op10_simhash": op10_simhash,
    "pipeline": pipeline,
}

ORACLES: dict[str, str] = {"op8_licences": licences.ORACLE}
