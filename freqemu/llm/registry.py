"""Queries over the given tables, one for each operator, and their SQL where SQL can say it."""

from __future__ import annotations

from .chat import OP10_SQL, op10_chat
from .decontaminate import OP1_SQL, op1_decontamination
from .language import op3_language
from .licences import op7_licences
from .media import op9_media
from .mixing import OP5_SQL, op5_mixing
from .neardup import OP2_SQL, op2_near_duplicates
from .pages import op4_main_text
from .quality import op8_quality
from .suffix_tree import op6_language_model


def queries() -> dict:
    return {f.__name__: f for f in (op1_decontamination, op2_near_duplicates, op3_language, op4_main_text, op5_mixing, op6_language_model, op7_licences, op8_quality, op9_media, op10_chat)}


def oracle_sql() -> dict[str, str]:
    return {"op1_decontamination": OP1_SQL, "op2_near_duplicates": OP2_SQL, "op5_mixing": OP5_SQL, "op10_chat": OP10_SQL}
