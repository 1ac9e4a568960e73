"""Queries of this subpackage, and SQL for those that SQL expresses."""

from softlanes.llm import bpe, exact_dedup, language, licenses, packing, quality, sharding, simhash, urls, vectors


def queries():
    return {
        "op1_sampled_splitters": sharding.op1_sampled_splitters,
        "op2_license_scan": licenses.op2_license_scan,
        "op3_pruned_graph": vectors.op3_pruned_graph,
        "op4_fourier_quality": quality.op4_fourier_quality,
        "op5_covering_simhash": simhash.op5_covering_simhash,
        "op6_recurrent_language": language.op6_recurrent_language,
        "op7_streaming_exact_dedup": exact_dedup.op7_streaming_exact_dedup,
        "op8_dominance_packing": packing.op8_dominance_packing,
        "op9_association_rules": urls.op9_association_rules,
        "op10_bpe_merge_rounds": bpe.op10_bpe_merge_rounds,
    }


def oracle_sql():
    return {"op2_license_scan": licenses.oracle_op2(), "op7_streaming_exact_dedup": exact_dedup.ORACLE_OP7}
