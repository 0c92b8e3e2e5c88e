"""Registry of the text operators' queries and of their SQL twins."""

from __future__ import annotations

from .decontaminate import OP6_SQL, op6_decontaminate
from .knn import OP10_SQL, op10_top_products
from .licenses import op7_licenses
from .mixing import OP1_SQL, op1_mix
from .near_dedup import op4_near_dedup
from .passages import op9_passages
from .pii import op5_surrogates
from .quality import op8_quality
from .toxicity import op2_toxicity
from .warc import OP3_SQL, op3_warc


def queries() -> dict:
    return {
        f.__name__: f
        for f in (op1_mix, op2_toxicity, op3_warc, op4_near_dedup, op5_surrogates, op6_decontaminate, op7_licenses, op8_quality, op9_passages, op10_top_products)
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_mix": OP1_SQL, "op6_decontaminate": OP6_SQL, "op3_warc": OP3_SQL, "op10_top_products": OP10_SQL}
