"""Common tables of the DuckDB twins."""

from __future__ import annotations

from cellwright.functions import lexing
from cellwright.functions.dialect import DUCK
from cellwright.sources import carriers

BASES = {
    "formulas": carriers.FORMULAS,
    "formulas_wide": carriers.FORMULAS_WIDE,
    "formula_edits": carriers.edits_sql(True),
    "prose": "SELECT doc_id AS formula_id, source AS workbook_id, text AS formula FROM documents",
}


def lexed(base: str = "formulas", more: str = "") -> str:
    """WITH clause: b (base), t (tokens), f (tokens, kinds), and more."""
    return f"""WITH b AS ({BASES[base]}),
        t AS (SELECT *, {lexing.lex(DUCK, 'formula')} AS tokens FROM b),
        f AS (SELECT *, {lexing.kinds(DUCK, 'tokens')} AS kinds FROM t){more} """


def sketched(base: str = "formulas", more: str = "") -> str:
    return lexed(base, f", s AS (SELECT *, {lexing.sketch(DUCK, 'tokens', 'kinds')} AS sketch FROM f){more}")
