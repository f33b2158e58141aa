"""Queries of the training-data operators and the SQL that checks those that SQL can express."""

from __future__ import annotations

from .bpe import op2_byte_bpe
from .decontaminate import OP8_SQL, op8_decontamination
from .hashforest import op3_neighbours
from .langmodel import op6_lm_scores
from .neardup import OP9_SQL, op9_neardup
from .pii import op1_pii
from .quality import op10_quality
from .revisit import OP4_SQL, op4_revisits
from .secrets import op7_secrets
from .toxicity import op5_toxicity

QUERIES = {
    "op1_pii": op1_pii,
    "op2_byte_bpe": op2_byte_bpe,
    "op3_neighbours": op3_neighbours,
    "op4_revisits": op4_revisits,
    "op5_toxicity": op5_toxicity,
    "op6_lm_scores": op6_lm_scores,
    "op7_secrets": op7_secrets,
    "op8_decontamination": op8_decontamination,
    "op9_neardup": op9_neardup,
    "op10_quality": op10_quality,
}

ORACLES: dict[str, str] = {
    "op4_revisits": OP4_SQL,
    "op8_decontamination": OP8_SQL,
    "op9_neardup": OP9_SQL,
}
