"""Queries of the corpus operators, and their SQL where SQL can express them."""

from __future__ import annotations

from deltafold.llm.anisotropic_ann import op9_nearest_neighbours
from deltafold.llm.bestfit_packing import op3_bestfit_packing
from deltafold.llm.content_sort import OP6_SQL, op6_exact_dedup
from deltafold.llm.debruijn_spans import op2_substring_dedup
from deltafold.llm.jaccard_join import op5_jaccard_join
from deltafold.llm.language_fusion import op7_language_id
from deltafold.llm.prefix_bpe import op10_bpe_codec
from deltafold.llm.quality_rules import op1_quality_classifier
from deltafold.llm.radix_suffixes import op4_suffix_dedup
from deltafold.llm.secret_crf import op8_secret_scan

QUERIES = {
    "op1_quality_classifier": op1_quality_classifier,
    "op2_substring_dedup": op2_substring_dedup,
    "op3_bestfit_packing": op3_bestfit_packing,
    "op4_suffix_dedup": op4_suffix_dedup,
    "op5_jaccard_join": op5_jaccard_join,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_language_id": op7_language_id,
    "op8_secret_scan": op8_secret_scan,
    "op9_nearest_neighbours": op9_nearest_neighbours,
    "op10_bpe_codec": op10_bpe_codec,
}

ORACLE_SQL: dict[str, str] = {"op6_exact_dedup": OP6_SQL}
