"""Seventeen user-noise operators as rewrites of token arrays.

The first six follow mistakes that the reference shows or names; the other eleven are this library's own choice. Each is
an expression that gives the corrupted text, or null where the operator does not apply.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .dialect import SPARK, Spark, ascii_upper
from .lexing import with_steps

#: op_id: (name, category, attested)
CATALOGUE = {
    "N01": ("arity-drop", "argument", True),
    "N02": ("arity-add", "argument", True),
    "N03": ("bracket-shift", "bracket", True),
    "N04": ("argument-swap", "argument", True),
    "N05": ("unquote-string", "string", True),
    "N06": ("logical-infix", "function", True),
    "N07": ("drop-close", "bracket", False),
    "N08": ("extra-close", "bracket", False),
    "N09": ("drop-open", "bracket", False),
    "N10": ("drop-separator", "separator", False),
    "N11": ("wrong-separator", "separator", False),
    "N12": ("broken-range", "reference", False),
    "N13": ("half-quote", "string", False),
    "N14": ("comparison-typo", "operator", False),
    "N15": ("operator-doubled", "operator", False),
    "N16": ("function-typo", "function", False),
    "N17": ("sheet-reference-broken", "reference", False),
}


def places(d: Spark) -> list[dict[str, str]]:
    """Helper columns over tokens, kinds; each step may use those before it.

    opens, shuts: places of brackets; depth: open brackets after each token; call, logical: first call, first AND or OR; *_close, *_seps: where its brackets
    close, its separators; shift, shift_to: a closing bracket before a separator, and where the argument after it ends."""
    idx = d.seq("1", d.size("tokens"))

    def first(cond: str) -> str:
        return d.at(d.keep(idx, "j", cond), "1")

    tj, dj = d.at("tokens", "j"), d.at("depth", "j")

    def close(p: str) -> str:
        return first(f"j > {p} + 1 and {tj} = ')' and {dj} = {d.at('depth', f'{p} + 1')} - 1")

    def seps(p: str) -> str:
        return d.keep(idx, "j", f"j > {p} + 1 and j < {p}_close and {tj} = ',' and {dj} = {d.at('depth', f'{p} + 1')}")

    opened, shut = (d.size(d.keep(x, "y", "y <= i")) for x in ("opens", "shuts"))
    kj = d.at("kinds", "j")
    return [
        {"opens": d.keep(idx, "j", f"{tj} = '('"), "shuts": d.keep(idx, "j", f"{tj} = ')'")},
        {"depth": d.each(idx, "i", f"{opened} - {shut}"), "call": first(f"{kj} = 'function'"), "logical": first(f"{kj} = 'function' and {ascii_upper(tj)} in ('AND', 'OR')")},
        {"call_close": close("call"), "logical_close": close("logical"), "shift": first(f"{tj} = ')' and {d.at('tokens', 'j + 1')} = ',' and {dj} >= 1")},
        {
            "call_seps": seps("call"),
            "logical_seps": seps("logical"),
            "shift_to": first(f"j > shift + 1 and (({tj} = ',' and {dj} = {d.at('depth', 'shift + 1')}) or ({tj} = ')' and {dj} = {d.at('depth', 'shift + 1')} - 1))"),
        },
    ]


def applies(d: Spark, op: str) -> str:
    """Whether an operator changes a formula in more than spaces and case, from the helper columns alone.

    Every rewrite takes out, adds or moves at least one mark or letter, but for the exchange of two equal arguments."""
    cond, _ = _operation(d, op)
    if op != "N04":
        return cond

    def bare(a: str, b: str) -> str:
        return ascii_upper(f"replace({d.join(d.cut('tokens', a, b))}, ' ', '')")

    one, two = d.at("call_seps", "1"), f"coalesce({d.at('call_seps', '2')}, call_close)"
    return f"({cond} and {bare('call + 2', f'{one} - 1')} <> {bare(f'{one} + 1', f'{two} - 1')})"


def rewrite(d: Spark, op: str) -> str:
    """Corrupted text, or null."""
    cond, out = _operation(d, op)
    return f"case when {cond} then {out} end"


def _operation(d: Spark, op: str) -> tuple[str, str]:
    """Where an operator has something to work on, and the corrupted text."""
    t, n = "tokens", d.size("tokens")
    idx = d.seq("1", n)

    def first(cond: str) -> str:
        return d.at(d.keep(idx, "j", cond), "1")

    def last(cond: str) -> str:
        xs = d.keep(idx, "j", cond)
        return d.at(xs, d.size(xs))

    def splice(a: str, new: list[str], b: str) -> str:
        """tokens up to a, new ones, tokens from b."""
        return d.join(d.cat(d.cut(t, "1", a), *([d.arr(*new)] if new else []), d.cut(t, b, n)))

    def when(cond: str, out: str) -> tuple[str, str]:
        return f"({cond})", out

    tj, kj = d.at(t, "j"), d.at("kinds", "j")
    n_seps, last_sep = d.size("call_seps"), d.at("call_seps", d.size("call_seps"))
    one, two = d.at("call_seps", "1"), f"coalesce({d.at('call_seps', '2')}, call_close)"
    string = first(f"{kj} = 'string' and {d.rx(tj, '^\"(?:[^\"]|\"\")+\"$')}")

    def replace_at(i: str, new: str) -> tuple[str, str]:
        return when(f"{i} is not null", splice(f"{i} - 1", [new], f"{i} + 1"))

    def drop_at(i: str) -> tuple[str, str]:
        return when(f"{i} is not null", splice(f"{i} - 1", [], f"{i} + 1"))

    def at(i: str) -> str:
        return d.at(t, i)

    if op == "N01":
        return when(f"call_close is not null and {n_seps} >= 1", splice(f"{last_sep} - 1", [], "call_close"))
    if op == "N02":
        start = f"(coalesce({last_sep}, call + 1) + 1)"
        return when("call_close > call + 2", d.join(d.cat(d.cut(t, "1", "call_close - 1"), d.arr("','"), d.cut(t, start, "call_close - 1"), d.cut(t, "call_close", n))))
    if op == "N03":
        return when("shift_to is not null", d.join(d.cat(d.cut(t, "1", "shift - 1"), d.cut(t, "shift + 1", "shift_to - 1"), d.arr("')'"), d.cut(t, "shift_to", n))))
    if op == "N04":
        swapped = d.cat(d.cut(t, "1", "call + 1"), d.cut(t, f"{one} + 1", f"{two} - 1"), d.arr("','"), d.cut(t, "call + 2", f"{one} - 1"), d.cut(t, two, n))
        return when(f"call_close is not null and {n_seps} >= 1", d.join(swapped))
    if op == "N05":
        return replace_at(string, f"substring({at(string)}, 2, length({at(string)}) - 2)")
    if op == "N06":
        sep = d.at("logical_seps", "1")
        parts = d.cat(d.cut(t, "1", "logical - 1"), d.cut(t, "logical + 2", f"{sep} - 1"), d.arr("' '", at("logical"), "' '"), d.cut(t, f"{sep} + 1", "logical_close - 1"), d.cut(t, "logical_close + 1", n))
        return when(f"logical_close is not null and {d.size('logical_seps')} >= 1", d.join(parts))
    if op == "N07":
        return drop_at(last(f"{tj} = ')'"))
    if op == "N08":
        return when(d.some(t, "x", "x = '('"), f"concat({d.join(t)}, ')')")
    if op == "N09":
        return drop_at(first(f"{tj} = '('"))
    if op == "N10":
        return drop_at(first(f"{tj} = ','"))
    if op == "N11":
        return replace_at(first(f"{tj} = ','"), "';'")
    if op == "N12":
        return drop_at(first(f"{tj} = ':' and {d.at('kinds', 'j - 1')} = 'cell' and {d.at('kinds', 'j + 1')} = 'cell'"))
    if op == "N13":
        return replace_at(string, f"substring({at(string)}, 1, length({at(string)}) - 1)")
    if op == "N14":
        i = first(f"{d.has(['<=', '>=', '<>'], tj)}")
        return replace_at(i, f"reverse({at(i)})")
    if op == "N15":
        i = first(f"j > 1 and {d.has(['+', '-', '*', '/', '&', '^'], tj)}")
        return replace_at(i, f"concat({at(i)}, {at(i)})")
    if op == "N16":
        x = at("call")
        a, b = f"substring({x}, 1, 1)", f"substring({x}, 2, 1)"
        typo = f"case when length({x}) >= 2 and {ascii_upper(a)} <> {ascii_upper(b)} then concat({b}, {a}, substring({x}, 3)) else concat({x}, substring({x}, length({x}), 1)) end"
        return replace_at("call", typo)
    if op == "N17":
        return drop_at(first(f"{tj} = '!' and {d.at('kinds', 'j - 1')} = 'sheet'"))
    raise KeyError(op)


def valid(d: Spark, out: str) -> str:
    """The rewrite, where it changes more than spaces and case."""

    def bare(x: str) -> str:
        return ascii_upper(f"replace({x}, ' ', '')")

    return f"case when {bare(out)} <> {bare(d.join('tokens'))} then {out} end"


def with_places(df: DataFrame) -> DataFrame:
    """Adds the helper columns to a table with tokens and kinds."""
    return with_steps(df, places(SPARK), HELPERS)


HELPERS = ["opens", "shuts", "depth", "call", "logical", "call_close", "logical_close", "shift", "call_seps", "logical_seps", "shift_to"]


def apply_operator(df: DataFrame, op: str) -> DataFrame:
    """Rows to which an operator applies, with noisy: their corrupted text."""
    out = with_places(df).withColumn("noisy_raw", F.expr(rewrite(SPARK, op)))
    # a filter is not pushed below a column that is not deterministic; pushed, its condition would be written out in full,
    # helper within helper, and grow without bound
    out = out.withColumns({"noisy": F.expr(valid(SPARK, "noisy_raw")), "row_no": F.monotonically_increasing_id()})
    return out.where("noisy IS NOT NULL AND row_no >= 0").drop("noisy_raw", "row_no", *HELPERS)


def pick(d: Spark, seed: int, key: str, ops: list[str]) -> str:
    """One of the applicable rewrites, columns named by ops, uniform by the keyed hash: struct op_id, noisy."""
    have = d.keep(d.arr(*(d.names(op_id=d.lit(o), noisy=o) for o in ops)), "x", "x.noisy is not null")
    return d.at(have, f"1 + ({d.u32(str(seed), key, "'operator'")} % greatest({d.size(have)}, 1))")


def user_noise(df: DataFrame, seed: int, key: str = "formula_id", ops: list[str] | None = None) -> DataFrame:
    """Adds op_id and noisy by one operator, uniform among those that apply; both null where none does.

    Which operators apply is told from the helper columns; only the one that is drawn rewrites the formula."""
    ops = ops or list(CATALOGUE)
    have = SPARK.keep(SPARK.arr(*(f"case when {applies(SPARK, o)} then '{o}' end" for o in ops)), "x", "x is not null")
    out = with_places(df).withColumn("have", F.expr(have))
    out = out.withColumn("op_id", F.expr(SPARK.at("have", f"1 + ({SPARK.u32(str(seed), key, "'operator'")} % greatest({SPARK.size('have')}, 1))")))
    chosen = " ".join(f"when '{o}' then {_operation(SPARK, o)[1]}" for o in ops)
    return out.withColumn("noisy", F.expr(f"case op_id {chosen} end")).drop("have", *HELPERS)


def catalogue(df: DataFrame) -> DataFrame:
    """op_id, name, category, attested, applies: of the formulas of a table with tokens and kinds, how many an operator changes."""
    found = F.filter(F.array(*(F.when(F.expr(applies(SPARK, o)), F.lit(o)) for o in CATALOGUE)), lambda x: x.isNotNull())
    met = with_places(df).select(F.explode(found).alias("op_id")).groupBy("op_id").agg(F.count(F.lit(1)).alias("n"))
    ops = df.sparkSession.createDataFrame([(k, *v) for k, v in CATALOGUE.items()], "op_id string, name string, category string, attested boolean")
    return ops.join(met, "op_id", "left").select("op_id", "name", "category", "attested", F.coalesce("n", F.lit(0)).cast("long").alias("applies"))
