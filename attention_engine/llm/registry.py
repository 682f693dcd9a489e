"""Queries and SQL of the training-data operators."""

from . import urlrules, warc
from .ctw import op7_lm_scoring
from .decontaminate import op5_benchmark_decontamination
from .langid import op6_language_id
from .linededup import op1_line_dedup
from .packing import op10_best_fit_packing
from .quality import op8_quality_rules
from .secrets import op9_secret_scans
from .simhash import op4_simhash_near_dedup

QUERIES = {
    "op1_line_dedup": op1_line_dedup,
    "op2_warc": warc.op2_warc,
    "op3_url_filters": urlrules.op3_url_filters,
    "op4_simhash_near_dedup": op4_simhash_near_dedup,
    "op5_benchmark_decontamination": op5_benchmark_decontamination,
    "op6_language_id": op6_language_id,
    "op7_lm_scoring": op7_lm_scoring,
    "op8_quality_rules": op8_quality_rules,
    "op9_secret_scans": op9_secret_scans,
    "op10_best_fit_packing": op10_best_fit_packing,
}
ORACLES = {"op2_warc": warc.SQL, "op3_url_filters": urlrules.SQL}
