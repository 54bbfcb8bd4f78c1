"""Registered queries of the corpus operators and the SQL for those that SQL can express."""

from tracedex.llm import contamination, licences
from tracedex.llm.binary import op8_training_order
from tracedex.llm.contamination import op7_decontamination
from tracedex.llm.fingerprints import op1_fingerprint_digests
from tracedex.llm.language import op9_language_mixture
from tracedex.llm.licences import op6_licence_scan
from tracedex.llm.near import op4_jaccard_join
from tracedex.llm.packing import op5_best_fit_packing
from tracedex.llm.private import op10_private_surrogates
from tracedex.llm.quality import op2_quality_rules
from tracedex.llm.substrings import op3_repeated_strings

_ALL = [op1_fingerprint_digests, op2_quality_rules, op3_repeated_strings, op4_jaccard_join, op5_best_fit_packing, op6_licence_scan, op7_decontamination, op8_training_order, op9_language_mixture, op10_private_surrogates]
QUERIES = {f.__name__: f for f in _ALL}
ORACLES = {"op6_licence_scan": licences.ORACLE, "op7_decontamination": contamination.ORACLE}
