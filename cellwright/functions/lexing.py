"""Lexer, token kinds, sketches, match normalisation and the domain pre-tokenizer, as array expressions.

Every function takes a dialect and SQL for its inputs and returns SQL; the `with_*` functions apply them to DataFrames.
A null formula has null tokens and a null sketch; an empty one has no tokens and an empty sketch.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dialect import SPARK, Spark, ascii_upper

#: tried in this order at every position; the last alternative makes the lexer total, so tokens concatenate to the text
UNITS = [
    ("string", r'"(?:[^"]|"")*"?'),
    ("quoted sheet", r"'(?:[^']|'')*'"),
    ("error", r"#[A-Z][A-Z0-9/]*[!?]?"),
    ("structured reference", r"\[(?:[^\[\]]|\[[^\[\]]*\])*\]"),
    ("anchored row", r"[$][0-9]{1,7}"),
    ("word", r"[$]?[\p{L}_][\p{L}\p{N}_.$]*"),
    ("number", r"[0-9]+(?:[.][0-9]+)?(?:[eE][-+]?[0-9]+)?|[.][0-9]+"),
    ("comparison", r"<=|>=|<>"),
    ("space", r"[ \t\r\n\f]+"),
    ("other", r"(?s:.)"),
]
LEX = "|".join(p for _, p in UNITS)
OPERATORS = ["+", "-", "*", "/", "^", "&", "=", "<", ">", "<=", ">=", "<>", "%"]
#: built-in functions known to the engine, with their least and most arguments (255: any number)
ARITY = {
    "SUM": (1, 255), "AVERAGE": (1, 255), "COUNT": (1, 255), "COUNTA": (1, 255), "COUNTIF": (2, 2), "SUMIF": (2, 3), "IF": (2, 3),
    "IFERROR": (2, 2), "ISERROR": (1, 1), "ISBLANK": (1, 1), "AND": (1, 255), "OR": (1, 255), "NOT": (1, 1), "VLOOKUP": (3, 4),
    "HLOOKUP": (3, 4), "INDEX": (2, 4), "MATCH": (2, 3), "ROUND": (2, 2), "LOG10": (1, 1), "ABS": (1, 1), "MIN": (1, 255), "MAX": (1, 255),
    "EDATE": (2, 2), "TODAY": (0, 0), "NOW": (0, 0), "DATE": (3, 3), "YEAR": (1, 1), "MONTH": (1, 1), "LEFT": (1, 2), "RIGHT": (1, 2),
    "MID": (3, 3), "LEN": (1, 1), "CONCATENATE": (1, 255), "TRIM": (1, 1), "PRODUCT": (1, 255), "TEXT": (2, 2),
}
FUNCTIONS = sorted(ARITY)


def lex(d: Spark, text: str) -> str:
    return d.rx_all(text, LEX)


def kinds(d: Spark, t: str) -> str:
    """Kind of each token, from its shape and its neighbours."""
    x, after, before = d.at(t, "i"), d.at(t, "i + 1"), d.at(t, "i - 1")
    colon = f"(coalesce({after}, '') = ':' or coalesce({before}, '') = ':')"
    case = f"""case
        when {d.rx(x, '^"')} then 'string'
        when {d.rx(x, "^'.")} then 'sheet'
        when {d.rx(x, '^#[A-Z]')} then 'error'
        when {d.rx(x, r'^\[.')} then 'structured'
        when {d.rx(x, '^[$][0-9]')} then 'cell'
        when {d.rx(x, r'^[$]?[\p{L}_]')} then case
            when {after} = '(' then 'function'
            when {after} = '!' then 'sheet'
            when {ascii_upper(x)} in ('TRUE', 'FALSE') then 'bool'
            when {d.rx(x, '^[$]?[A-Za-z]{1,3}[$]?[0-9]{1,7}$')} then 'cell'
            when {d.rx(x, '^[$]?[A-Za-z]{1,3}$')} and {colon} then 'cell'
            else 'identifier' end
        when {d.rx(x, '^[0-9]{1,7}$')} and {colon} then 'cell'
        when {d.rx(x, '^[.]?[0-9]')} then 'number'
        when {d.rx(x, '^[ \t\r\n\f]')} then 'space'
        when {d.has(OPERATORS, x)} then 'op'
        else 'punct' end"""
    return d.each(d.seq("1", d.size(t)), "i", case)


MASKED = ("string", "number", "cell")


def sketch(d: Spark, t: str, k: str, mask: tuple[str, ...] = MASKED, keep_space: bool = False) -> str:
    """Constants and references as their kinds, identifiers in capitals; spaces dropped unless kept."""
    kind = d.at(k, "i")
    space = "" if keep_space else f"when {kind} = 'space' then '' "
    return d.join(d.each(d.seq("1", d.size(t)), "i", f"case {space}when {d.has(list(mask), kind)} then {kind} else {ascii_upper(d.at(t, 'i'))} end"))


def _solid(d: Spark, t: str, k: str) -> str:
    """Places of the tokens that are no space."""
    return d.keep(d.seq("1", d.size(t)), "i", f"{d.at(k, 'i')} <> 'space'")


def sketch_match_form(d: Spark, t: str, k: str, fold_sign: bool = True, mask_sheets: bool = False) -> str:
    """The sketch for comparing completions: a sign before a number belongs to it where no operand precedes."""
    mask = [*MASKED, *(["sheet"] if mask_sheets else [])]

    def form(s: str) -> str:
        here, before, after = d.at(s, "j"), d.at(s, "j - 1"), d.at(s, "j + 1")
        opens = f"(j = 1 or {d.at(k, before)} = 'op' or {d.has(['(', ',', '{', ';'], d.at(t, before))})"
        sign = f"({d.has(['-', '+'], d.at(t, here))} and coalesce({d.at(k, after)} = 'number', false) and {opens})" if fold_sign else "false"
        body = f"case when {sign} then '' when {d.has(mask, d.at(k, here))} then {d.at(k, here)} else {ascii_upper(d.at(t, here))} end"
        return d.join(d.each(d.seq("1", d.size(s)), "j", body))

    return d.bind("solid", _solid(d, t, k), form)


def match_form(d: Spark, t: str, k: str) -> str:
    """Normal form for exact match: references and identifiers in capitals, white space tokens dropped, strings as they are."""
    kind = d.at(k, "i")
    return d.join(d.each(d.seq("1", d.size(t)), "i", f"case when {kind} = 'space' then '' when {kind} in ('string', 'number') then {d.at(t, 'i')} else {ascii_upper(d.at(t, 'i'))} end"))


RUN = r"\p{L}+"
PIECE = rf"[0-9]|{RUN}|(?s:.)"


def pretokens(d: Spark, text: str, lowercase: bool = True) -> str:
    """Digits, letter runs, single spaces and marks; letter runs that are no built-in function are left to BPE."""
    return d.rx_all(f"lower({text})" if lowercase else text, PIECE)


def model_tokens(d: Spark, t: str, k: str, split_ref_letters: bool = True) -> str:
    """Pretokens of each lexer token (an array of arrays); column letters of references single, if wanted."""
    own = pretokens(d, d.at(t, "i"))
    return d.each(d.seq("1", d.size(t)), "i", f"case when {d.at(k, 'i')} = 'cell' then {d.chars(f'lower({d.at(t, "i")})')} else {own} end" if split_ref_letters else own)


def is_word(d: Spark, piece: str) -> str:
    """Whether a pretoken is left to BPE."""
    return f"({d.rx(piece, r'^\p{L}')} and not {d.has([f.lower() for f in FUNCTIONS], f'lower({piece})')})"


def balanced(d: Spark, t: str) -> str:
    """Brackets close in order and all of them; strings are single tokens, so brackets within them do not count.

    In order: the k-th closing bracket stands after the k-th opening one."""
    idx = d.seq("1", d.size(t))
    at = d.arr(d.names(o=d.keep(idx, "i", f"{d.at(t, 'i')} = '('"), c=d.keep(idx, "i", f"{d.at(t, 'i')} = ')'")))
    early = d.some(d.seq("1", d.size("z.c")), "k", f"{d.at('z.o', 'k')} > {d.at('z.c', 'k')}")
    return d.at(d.each(at, "z", f"({d.size('z.o')} = {d.size('z.c')} and not {early})"), "1")


def well_formed(d: Spark, t: str, k: str) -> str:
    """Balanced brackets, closed strings, no dangling or doubled binary operator, no empty argument after a separator."""
    binary = ["*", "/", "^", "&", "=", "<", ">", "<=", ">=", "<>"]

    def fine(s: str) -> str:
        here, after = d.at(t, d.at(s, "j")), d.at(t, d.at(s, "j + 1"))
        idx = d.seq("1", d.size(s))
        bad = f"({d.has([*binary, '+', '-'], here)} and j > 1 and ({after} is null or {d.has([*binary, ')', ','], after)})) or ({here} = ',' and ({after} is null or {d.has([')', ','], after)}))"
        return f"({balanced(d, t)} and {closed} and not {d.some(idx, 'j', bad)})"

    closed = f"not {d.some(t, 'x', f'{d.rx("x", "^[\"]")} and not {d.rx("x", '^"(?:[^"]|"")*"$')}')}"
    return d.bind("kind", k, lambda k: d.bind("solid", _solid(d, t, k), fine))


def with_tokens(df: DataFrame, text: str = "formula") -> DataFrame:
    """Adds tokens and kinds (parallel arrays)."""
    return df.withColumn("tokens", F.expr(lex(SPARK, text))).withColumn("kinds", F.expr(kinds(SPARK, "tokens")))


def with_steps(df: DataFrame, steps: list[dict[str, str]], keep: list[str]) -> DataFrame:
    """Adds the kept columns of steps whose columns may use those of the steps before."""
    own = [{"tokens": "tokens", "kinds": "kinds"}]  # what they read, bound for the same reason
    out = df.withColumn("_steps", F.expr(SPARK.bound(own + steps)))
    return out.withColumns({c: F.col("_steps")[c] for c in keep}).drop("_steps")


def key128(c: str):
    """128-bit key of a text, empty for null. Never null: a join on it needs no null test, which Catalyst would push
    down with the whole expression of the sketch written out in it."""
    return F.coalesce(F.unhex(F.md5(c)), F.lit(b""))


def with_sketch(df: DataFrame, text: str = "formula", **spec) -> DataFrame:
    """Adds sketch and its 128-bit key."""
    out = df if "kinds" in df.columns else with_tokens(df, text)
    return out.withColumn("sketch", F.expr(sketch(SPARK, "tokens", "kinds", **spec))).withColumn("sketch_key", key128("sketch"))


def register(spark) -> None:
    """lex(text) and sketch(text) for SQL users; the bodies are inlined, so Catalyst sees plain expressions."""
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION lex(text STRING) RETURNS ARRAY<STRING> RETURN {lex(SPARK, 'text')}")
    body = sketch(SPARK, "t", "k")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch(text STRING) RETURNS STRING RETURN (SELECT {body} FROM (SELECT t, {kinds(SPARK, 't')} AS k FROM (SELECT {lex(SPARK, 'text')} AS t)))")
