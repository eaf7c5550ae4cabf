"""The queries of this subpackage and their SQL."""

from __future__ import annotations

import crowdrank.llm.ann as ann
import crowdrank.llm.decontamination as decontamination
import crowdrank.llm.html_text as html_text
import crowdrank.llm.jaccard_join as jaccard_join
import crowdrank.llm.language_id as language_id
import crowdrank.llm.line_dedup as line_dedup
import crowdrank.llm.lm_scoring as lm_scoring
import crowdrank.llm.packing as packing
import crowdrank.llm.substring_dedup as substring_dedup
import crowdrank.llm.token_output as token_output

QUERIES = {
    "op1_additive_quantisation": ann.op1_additive_quantisation,
    "op2_line_dedup": line_dedup.op2_line_dedup,
    "op3_jaccard_join": jaccard_join.op3_jaccard_join,
    "op4_packing": packing.op4_packing,
    "op5_language_id": language_id.op5_language_id,
    "op7_decontamination": decontamination.op7_decontamination,
    "op6_lm_scoring": lm_scoring.op6_lm_scoring,
    "op8_token_output": token_output.op8_token_output,
    "op9_html_extraction": html_text.op9_html_extraction,
    "op10_substring_dedup": substring_dedup.op10_substring_dedup,
}
SQL = {
    "op3_jaccard_join": jaccard_join.SQL,
    "op2_line_dedup": line_dedup.SQL,
    "op6_lm_scoring": lm_scoring.SQL,
    "op7_decontamination": decontamination.SQL,
    "op10_substring_dedup": substring_dedup.SQL,
}
