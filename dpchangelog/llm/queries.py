"""The queries of this subpackage and their SQL, for __spark_entry__.py."""

from __future__ import annotations

from .common import prepare, table


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_token_records(spark, sf_dir):
    from .record_files import op1

    return op1(spark, table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"), 2)


def op2_token_counts(spark, sf_dir):
    from .token_counts import op2

    return op2(spark, table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"))


def op3_line_dedup(spark, sf_dir):
    from .line_dedup import op3

    return op3(spark, table(spark, sf_dir, "documents"))


def op4_quality_rules(spark, sf_dir):
    from .quality_rules import op4

    return op4(spark, table(spark, sf_dir, "documents"))


def op5_quality_classifier(spark, sf_dir):
    from .quality_classifier import op5

    return op5(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_embedding_dedup(spark, sf_dir):
    from .embedding_dedup import op6

    return op6(spark, table(spark, sf_dir, "embeddings"))


def op7_vector_packing(spark, sf_dir):
    from .packing import op7

    return op7(spark, table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"))


def op8_piece_bpe(spark, sf_dir):
    from .piece_bpe import op8

    return op8(spark, table(spark, sf_dir, "documents"), _vocabulary("piece_bpe_32k.model"))


def op9_lm_scoring(spark, sf_dir):
    from .lm_scoring import op9

    return op9(spark, sf_dir)


def op10_simhash(spark, sf_dir):
    from .simhash import op10

    return op10(spark, table(spark, sf_dir, "documents"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {k: v for k, v in globals().items() if k == "pipeline" or k.startswith("op") and callable(v)}


def oracle_sql():
    from . import line_dedup

    return {"op3_line_dedup": line_dedup.SQL}
