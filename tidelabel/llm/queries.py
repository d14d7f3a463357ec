"""The operators' queries, by name."""

from tidelabel.llm import bpe, language, line_dedup, minhash, packing, quality_model, quality_rules, sharding, toxicity, vectors

QUERIES = {
    "op1_language": language.op1_language,
    "op2_size_tiered": sharding.op2_size_tiered,
    "op3_bpe_trie": bpe.op3_bpe_trie,
    "op4_packing": packing.op4_packing,
    "op5_minhash": minhash.op5_minhash,
    "op6_permutation_index": vectors.op6_permutation_index,
    "op7_deletion_lines": line_dedup.op7_deletion_lines,
    "op8_risk_rules": quality_rules.op8_risk_rules,
    "op9_kneser_ney": toxicity.op9_kneser_ney,
    "op10_ordinal": quality_model.op10_ordinal,
}
ORACLES: dict[str, str] = {
    "op7_deletion_lines": line_dedup.ORACLE,
}
