"""The queries of this folder and their SQL."""

from __future__ import annotations

from .decontaminate import op3_decontamination
from .licences import op10_licences
from .neardup import OP6_SQL, op6_near_duplicates
from .packing import op7_packing
from .pii import op9_pii
from .quality import op2_quality
from .secrets import op5_secrets
from .tokens import op1_token_counts

from .topk import OP8_SQL, op8_topk
from .toxicity import op4_toxicity


def queries() -> dict:
    return {f.__name__: f for f in (op1_token_counts, op2_quality, op3_decontamination, op4_toxicity, op5_secrets, op6_near_duplicates, op7_packing, op8_topk, op9_pii, op10_licences)}


def oracle_sql() -> dict[str, str]:
    return {"op6_near_duplicates": OP6_SQL, "op8_topk": OP8_SQL}
