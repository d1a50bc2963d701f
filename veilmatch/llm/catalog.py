"""Registered queries of this subpackage and their SQL."""

from veilmatch.llm.bitsliced import OP2_SQL, op2_exact_top_k
from veilmatch.llm.chat import OP10_SQL, op10_chat_formatting
from veilmatch.llm.contamination import op8_decontamination
from veilmatch.llm.language import op5_language_id
from veilmatch.llm.licenses import op1_license_scan
from veilmatch.llm.packing import op9_best_fit_packing
from veilmatch.llm.secrets import op4_secret_scan
from veilmatch.llm.simhash import op7_simhash_near_dedup
from veilmatch.llm.substrings import op3_substring_dedup
from veilmatch.llm.suffixes import op6_suffix_dedup

QUERIES = {
    "op1_license_scan": op1_license_scan,
    "op2_exact_top_k": op2_exact_top_k,
    "op3_substring_dedup": op3_substring_dedup,
    "op4_secret_scan": op4_secret_scan,
    "op5_language_id": op5_language_id,
    "op6_suffix_dedup": op6_suffix_dedup,
    "op7_simhash_near_dedup": op7_simhash_near_dedup,
    "op8_decontamination": op8_decontamination,
    "op9_best_fit_packing": op9_best_fit_packing,
    "op10_chat_formatting": op10_chat_formatting,
}
SQL = {"op2_exact_top_k": OP2_SQL, "op10_chat_formatting": OP10_SQL}
