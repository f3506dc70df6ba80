"""The registered query of each operator, and its SQL where SQL can express it."""

from __future__ import annotations

from pairbundle.llm.exact_dedup import ORACLE_OP10, op10_exact_dedup
from pairbundle.llm.grammar import op2_grammar_token_output
from pairbundle.llm.media import op6_media_columns
from pairbundle.llm.mixing import ORACLE_OP1, op1_source_mixing
from pairbundle.llm.packing import op5_best_fit_packing
from pairbundle.llm.pii import op9_personal_data
from pairbundle.llm.quality import op3_quality_classifier
from pairbundle.llm.simhash import op4_simhash_near_dedup
from pairbundle.llm.toxicity import op8_toxicity_classifier
from pairbundle.llm.url_filter import ORACLE_OP7, op7_url_filter

_ALL = (op1_source_mixing, op2_grammar_token_output, op3_quality_classifier, op4_simhash_near_dedup, op5_best_fit_packing, op6_media_columns, op7_url_filter, op8_toxicity_classifier, op9_personal_data, op10_exact_dedup)
QUERIES = {f.__name__: f for f in _ALL}
ORACLE_SQL = {"op1_source_mixing": ORACLE_OP1, "op7_url_filter": ORACLE_OP7, "op10_exact_dedup": ORACLE_OP10}
