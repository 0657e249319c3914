"""Queries of this subpackage and, where SQL can express them, their SQL."""

from .decontaminate import OP8_SQL, op8_decontaminate
from .html_extract import op1_html_extract
from .langid import op2_language_id
from .line_dedup import OP4_SQL, op4_line_dedup
from .packing import op6_best_fit_packing
from .quality_rules import op5_quality_rules
from .quality_trees import op3_quality_trees
from .simhash import op9_simhash_bktree
from .substring_dedup import OP10_SQL, op10_substring_dedup
from .toxicity import op7_toxicity

QUERIES = {
    "op1_html_extract": op1_html_extract,
    "op2_language_id": op2_language_id,
    "op3_quality_trees": op3_quality_trees,
    "op4_line_dedup": op4_line_dedup,
    "op5_quality_rules": op5_quality_rules,
    "op6_best_fit_packing": op6_best_fit_packing,
    "op7_toxicity": op7_toxicity,
    "op8_decontaminate": op8_decontaminate,
    "op9_simhash_bktree": op9_simhash_bktree,
    "op10_substring_dedup": op10_substring_dedup,
}
ORACLES = {"op4_line_dedup": OP4_SQL, "op8_decontaminate": OP8_SQL, "op10_substring_dedup": OP10_SQL}
