"""The queries of this subpackage and their SQL, by name."""

from __future__ import annotations

from sevenfold.llm.chat import op5_chat_format
from sevenfold.llm.decontaminate import SQL_OP8, op8_decontaminate
from sevenfold.llm.exact_dedup import SQL_OP4, op4_exact_dedup
from sevenfold.llm.language import op1_language
from sevenfold.llm.mixing import SQL_OP7, op7_mixing
from sevenfold.llm.secrets import SQL_OP10, op10_secrets
from sevenfold.llm.simhash import op9_simhash
from sevenfold.llm.token_counts import op3_token_counts
from sevenfold.llm.toxicity import op2_toxicity
from sevenfold.llm.warc import SQL_OP6, op6_warc

QUERIES = {
    "op1_language": op1_language,
    "op2_toxicity": op2_toxicity,
    "op3_token_counts": op3_token_counts,
    "op4_exact_dedup": op4_exact_dedup,
    "op5_chat_format": op5_chat_format,
    "op6_warc": op6_warc,
    "op7_mixing": op7_mixing,
    "op8_decontaminate": op8_decontaminate,
    "op9_simhash": op9_simhash,
    "op10_secrets": op10_secrets,
}

#: The others are tested against brute force, round trips or held-out accuracy.
ORACLES = {
    "op4_exact_dedup": SQL_OP4,
    "op6_warc": SQL_OP6,
    "op7_mixing": SQL_OP7,
    "op8_decontaminate": SQL_OP8,
    "op10_secrets": SQL_OP10,
}
