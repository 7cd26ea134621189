"""Queries and SQL of this subpackage."""

from __future__ import annotations

from loadshard.llm.latentdecon import op7_latent_decontamination
from loadshard.llm.linededup import op4_fuzzy_lines
from loadshard.llm.mixing import op6_multinomial_blocks
from loadshard.llm.neighbours import op9_neighbour_votes
from loadshard.llm.oracles import ORACLES
from loadshard.llm.secretspans import op8_secret_links
from loadshard.llm.simhash import op5_simhash_golay
from loadshard.llm.surrogates import op3_surrogates
from loadshard.llm.tokencount import op10_token_counts
from loadshard.llm.urlrules import op2_redirect_equivalence
from loadshard.llm.weightedsampling import op1_weighted_sampling

QUERIES = {
    "op1_weighted_sampling": op1_weighted_sampling,
    "op2_redirect_equivalence": op2_redirect_equivalence,
    "op3_surrogates": op3_surrogates,
    "op4_fuzzy_lines": op4_fuzzy_lines,
    "op5_simhash_golay": op5_simhash_golay,
    "op6_multinomial_blocks": op6_multinomial_blocks,
    "op7_latent_decontamination": op7_latent_decontamination,
    "op8_secret_links": op8_secret_links,
    "op9_neighbour_votes": op9_neighbour_votes,
    "op10_token_counts": op10_token_counts,
}

__all__ = ["ORACLES", "QUERIES"]
