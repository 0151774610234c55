"""The dealt operators' queries and their SQL, for __spark_entry__.py."""

from __future__ import annotations

from driftlattice.llm import context_tree, decontaminate, jaccard, language, lattice_dedup, licences, mixing, private_terms, substring, toxicity

QUERIES = {
    "op1_lattice_dedup": lattice_dedup.query,
    "op2_context_tree": context_tree.query,
    "op3_private_terms": private_terms.query,
    "op4_substring": substring.query,
    "op5_toxicity": toxicity.query,
    "op6_mixing": mixing.query,
    "op7_jaccard": jaccard.query,
    "op8_language": language.query,
    "op9_licences": licences.query,
    "op10_decontaminate": decontaminate.query,
}
ORACLES = {"op6_mixing": mixing.SQL}
