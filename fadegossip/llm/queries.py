"""The queries of this subpackage and, where SQL can express them, their DuckDB counterparts."""

from __future__ import annotations

from fadegossip.llm import chats
from fadegossip.llm.digest import op5_digest
from fadegossip.llm.mixing import op10_mixing
from fadegossip.llm.outliers import op9_outliers
from fadegossip.llm.pages import op2_pages
from fadegossip.llm.pieces import op1_pieces
from fadegossip.llm.quality import op6_quality
from fadegossip.llm.simhash import op3_simhash
from fadegossip.llm.substrings import op4_substrings
from fadegossip.llm.toxicity import op7_toxicity

QUERIES = {
    "op1_pieces": op1_pieces,
    "op2_pages": op2_pages,
    "op3_simhash": op3_simhash,
    "op4_substrings": op4_substrings,
    "op5_digest": op5_digest,
    "op6_quality": op6_quality,
    "op7_toxicity": op7_toxicity,
    "op8_chats": chats.op8_chats,
    "op9_outliers": op9_outliers,
    "op10_mixing": op10_mixing,
}

ORACLES: dict[str, str] = {"op8_chats": chats.ORACLE}
