"""The registered queries of the document operators, and SQL for those that SQL can express."""

from __future__ import annotations

from . import decontaminate, quality_rules
from .decontaminate import op3_decontaminate
from .license_scan import op8_license_scan
from .mixing import op10_mixing
from .ngram_join import op6_ngram_join
from .quality_rules import op1_quality_rules
from .seed_extend import op9_seed_extend
from .sharding import op4_sharding
from .suffix_dedup import op2_suffix_dedup
from .surrogates import op7_surrogates
from .token_counts import op5_token_counts

QUERIES = {f.__name__: f for f in (op1_quality_rules, op2_suffix_dedup, op3_decontaminate, op4_sharding, op5_token_counts, op6_ngram_join, op7_surrogates, op8_license_scan, op9_seed_extend, op10_mixing)}
ORACLES: dict[str, str] = {"op1_quality_rules": quality_rules.ORACLE_SQL, "op3_decontaminate": decontaminate.ORACLE_SQL}
