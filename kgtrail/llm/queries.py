"""The queries of this subpackage and, where SQL can express one, its DuckDB twin."""

from __future__ import annotations

from kgtrail.llm import op2_decontaminate as op2
from kgtrail.llm import op4_chat_views as op4
from kgtrail.llm.op1_bpe import op1_bpe
from kgtrail.llm.op2_decontaminate import op2_decontaminate
from kgtrail.llm.op3_token_files import op3_token_files
from kgtrail.llm.op4_chat_views import op4_chat_views
from kgtrail.llm.op5_reshard import op5_reshard
from kgtrail.llm.op6_pii import op6_pii
from kgtrail.llm.op7_repeats import op7_repeats
from kgtrail.llm.op8_near_copies import op8_near_copies
from kgtrail.llm.op9_embeddings import op9_embeddings
from kgtrail.llm.op10_toxicity import op10_toxicity

QUERIES = {
    "op1_bpe": op1_bpe,
    "op2_decontaminate": op2_decontaminate,
    "decontamination_proximity": op2.decontamination_proximity,
    "op3_token_files": op3_token_files,
    "op4_chat_views": op4_chat_views,
    "op5_reshard": op5_reshard,
    "op6_pii": op6_pii,
    "op7_repeats": op7_repeats,
    "op8_near_copies": op8_near_copies,
    "op9_embeddings": op9_embeddings,
    "op10_toxicity": op10_toxicity,
}
SQL = {"op2_decontaminate": op2.SQL, "op4_chat_views": op4.SQL}
