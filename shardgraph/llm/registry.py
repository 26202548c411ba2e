"""Queries and oracle SQL of the corpus operators."""

from shardgraph.llm import embeddings, fingerprints, language_model, licenses, line_dedup, mixing, packing, quality, simhash, toxicity


def _pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {
        "op1_embedding_dedup": embeddings.query,
        "op2_packing": packing.query,
        "op3_toxicity": toxicity.query,
        "op4_line_dedup": line_dedup.query,
        "op5_simhash_dedup": simhash.query,
        "op6_source_mixing": mixing.query,
        "op7_document_fingerprints": fingerprints.query,
        "op8_license_scan": licenses.query,
        "op9_quality_classifier": quality.query,
        "op10_lm_scoring": language_model.query,
        "pipeline": _pipeline,
    }


def oracle_sql():
    return {"op1_embedding_dedup": embeddings.ORACLE, "op4_line_dedup": line_dedup.ORACLE, "op6_source_mixing": mixing.ORACLE}
