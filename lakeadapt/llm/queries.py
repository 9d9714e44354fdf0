"""The queries of the corpus operators and their SQL, as __spark_entry__ registers them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from lakeadapt.llm import ann, bpe, jaccard, linededup, mixing, planes, quality, sharding, urlfilter, warc


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    import corpus_pipeline

    return {
        "op1_line_dedup": linededup.op1_line_dedup,
        "op2_warc_archive": warc.op2_warc_archive,
        "op3_jaccard_join": jaccard.op3_jaccard_join,
        "op4_mix_sources": mixing.op4_mix_sources,
        "op5_byte_bpe": bpe.op5_byte_bpe,
        "op6_bit_planes": planes.op6_bit_planes,
        "op7_url_filters": urlfilter.op7_url_filters,
        "op8_feistel_shards": sharding.op8_feistel_shards,
        "op9_line_first_quality": quality.op9_line_first_quality,
        "op10_ivf_pq": ann.op10_ivf_pq,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_warc_archive": warc.ORACLE,
        "op3_jaccard_join": jaccard.ORACLE,
        "op4_mix_sources": mixing.ORACLE,
        "op7_url_filters": urlfilter.ORACLE,
    }
