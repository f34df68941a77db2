"""The queries of the corpus operators and their DuckDB twins."""

from __future__ import annotations

from .bit_packing import op3_bit_packing
from .chat_format import OP5_SQL, op5_chat_format
from .html_content import op10_html_content
from .jaccard_join import OP7_SQL, op7_jaccard_join
from .length_buckets import op2_length_buckets
from .pii_pseudonyms import op1_pii_pseudonyms
from .positional_index import OP6_SQL, op6_positional_index, op6_proximity
from .quality_classifier import op4_quality_classifier
from .rule_ledger import OP8_ABLATION_SQL, OP8_SQL, op8_policy_ablations, op8_rule_ledger
from .url_templates import OP9_SQL, op9_url_templates


def queries():
    return {
        "op1_pii_pseudonyms": op1_pii_pseudonyms,
        "op2_length_buckets": op2_length_buckets,
        "op3_bit_packing": op3_bit_packing,
        "op4_quality_classifier": op4_quality_classifier,
        "op5_chat_format": op5_chat_format,
        "op6_positional_index": op6_positional_index,
        "op6_proximity": op6_proximity,
        "op7_jaccard_join": op7_jaccard_join,
        "op8_rule_ledger": op8_rule_ledger,
        "op8_policy_ablations": op8_policy_ablations,
        "op9_url_templates": op9_url_templates,
        "op10_html_content": op10_html_content,
    }


def oracle_sql():
    return {
        "op5_chat_format": OP5_SQL,
        "op6_positional_index": OP6_SQL,
        "op7_jaccard_join": OP7_SQL,
        "op8_rule_ledger": OP8_SQL,
        "op8_policy_ablations": OP8_ABLATION_SQL,
        "op9_url_templates": OP9_SQL,
    }
