"""The queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from . import chat, licenses, media, packing, pii, quality, sharding, simhash, warc, wfst


def _pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        "op1_pii_boosting": pii.op1_pii_boosting,
        "op2_sentencepiece_wfst": wfst.op2_sentencepiece_wfst,
        "op3_warc_dictionary": warc.op3_warc_dictionary,
        "op4_quality_rules": quality.op4_quality_rules,
        "op5_image_copies": media.op5_image_copies,
        "op6_best_fit_packing": packing.op6_best_fit_packing,
        "op7_two_pass_shuffle": sharding.op7_two_pass_shuffle,
        "op8_simhash_trie": simhash.op8_simhash_trie,
        "op9_chat_prefix_targets": chat.op9_chat_prefix_targets,
        "op10_license_scan": licenses.op10_license_scan,
        "pipeline": _pipeline,
    }


def oracle_sql() -> dict[str, str]:
    return {"op3_warc_dictionary": warc.ORACLE_OP3, "op4_quality_rules": quality.ORACLE_OP4, "op9_chat_prefix_targets": chat.ORACLE_OP9}
