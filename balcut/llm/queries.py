"""The registered queries of the corpus operators."""

from __future__ import annotations

from .chat import OP9_SQL, op9_chat_format
from .decontaminate import op2_benchmark_decontamination
from .pieces import op8_sentencepiece
from .privacy import op3_private_data
from .quality import op10_quality_rules
from .secrets import op4_secret_scan
from .simhash import op1_simhash_duplicates
from .toxicity import op6_toxicity
from .urls import OP5_SQL, op5_url_filter
from .warc import OP7_SQL, op7_warc_bundles


def queries() -> dict:
    return {
        "op1_simhash_duplicates": op1_simhash_duplicates,
        "op2_benchmark_decontamination": op2_benchmark_decontamination,
        "op3_private_data": op3_private_data,
        "op4_secret_scan": op4_secret_scan,
        "op5_url_filter": op5_url_filter,
        "op6_toxicity": op6_toxicity,
        "op7_warc_bundles": op7_warc_bundles,
        "op8_sentencepiece": op8_sentencepiece,
        "op9_chat_format": op9_chat_format,
        "op10_quality_rules": op10_quality_rules,
    }


def oracle_sql() -> dict[str, str]:
    return {"op5_url_filter": OP5_SQL, "op7_warc_bundles": OP7_SQL, "op9_chat_format": OP9_SQL}
