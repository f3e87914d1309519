"""Work on formulas by their shape: the text with every ASCII digit as 0.

No rule of the lexer, of kinds, of well-formedness or of the noise operators asks which digit stands at a place, only
whether one does; two tests compare texts, and are made again on the formula itself (equal arguments in N04, digits in what
a sketch leaves as it is). So tokens are cut at the same places, and the costly helper columns are made once a shape and
joined to the formulas. Where there are as many shapes as formulas this costs a shuffle more and is still right.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lexing, noise
from .dialect import SPARK

#: up to so many shapes are broadcast
FEW = 50_000
#: what the span masks and the rewrites read beside the tokens
READ = ["firsts", "total", "kinds", "call", "call_close", "call_seps", "logical", "logical_close", "logical_seps", "shift", "shift_to"]


def shape(text: str):
    return F.translate(text, "123456789", "000000000")


def known(df: DataFrame, text: str = "formula") -> DataFrame:
    """shape, ok (well formed), shape_sketch, have (operators that apply), same (N04 exchanges arguments that look equal), and
    what the rewrites and the span masks (firsts: first sub-token of each token; total: sub-tokens) read, of all shapes of a table; kept, as it is read again."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    # the texts are kept, so that the columns below are made over all cores from them
    texts = df.where(F.col(text).isNotNull()).select(shape(text).alias("shape")).distinct().repartition(cores * 2, "shape")
    lexed = lexing.with_tokens(texts, "shape")
    placed = noise.with_places(lexed.withColumn("ok", F.expr(lexing.well_formed(SPARK, "tokens", "kinds"))).withColumn("shape_sketch", F.expr(lexing.sketch(SPARK, "tokens", "kinds"))))
    counts = SPARK.each(lexing.model_tokens(SPARK, "tokens", "kinds"), "x", f"cast({SPARK.size('x')} as bigint)")
    first = SPARK.each(SPARK.seq("1", SPARK.size("counts")), "i", f"1 + {SPARK.sum(SPARK.cut('counts', '1', 'i - 1'))}")
    placed = lexing.with_steps(placed, [{"counts": counts}, {"firsts": first, "total": SPARK.sum("counts")}], ["firsts", "total"])
    have = SPARK.keep(SPARK.arr(*(f"case when {noise._operation(SPARK, o)[0] if o == 'N04' else noise.applies(SPARK, o)} then '{o}' end" for o in noise.CATALOGUE)), "x", "x is not null")
    same = f"coalesce({noise._operation(SPARK, 'N04')[0]} and not {noise.applies(SPARK, 'N04')}, false)"
    out = placed.select("shape", "ok", "shape_sketch", F.expr(have).alias("have"), F.expr(same).alias("same"), *READ).persist()
    return F.broadcast(out) if out.count() <= FEW else out


def with_noise(df: DataFrame, seed: int | str, key: str = "formula_id", ops: list[str] | None = None, text: str = "formula", shapes: DataFrame | None = None, only_ok: bool = False, on: str = "true", keep: tuple[str, ...] = ()) -> DataFrame:
    """df with op_id and noisy as noise.user_noise gives them, from texts alone. shapes: known(...) of a table that has at
    least the texts of this one; only_ok: rows that are well formed; on: a condition on
    rows, both columns are null elsewhere; keep: columns of shapes to keep."""
    shapes = known(df, text) if shapes is None else shapes
    rows = df.withColumn("shape", shape(text))
    rows = rows.join(shapes.where("ok"), "shape") if only_ok else rows.join(shapes, "shape", "left")
    tokens = lexing.lex(SPARK, text)
    have = f"case when same and not {SPARK.bind('tokens', tokens, lambda _: noise.applies(SPARK, 'N04'))} then filter(have, o -> o <> 'N04') else have end"
    if ops:
        have = f"filter({have}, o -> o in ({', '.join(map(SPARK.lit, ops))}))"
    at = f"1 + ({SPARK.u32(str(seed), key, "'operator'")} % greatest({SPARK.size('h')}, 1))"
    drawn = rows.withColumn("op_id", F.expr(f"case when {on} then {SPARK.bind('h', have, lambda _: SPARK.at('h', at))} end"))
    chosen = " ".join(f"when '{o}' then {noise._operation(SPARK, o)[1]}" for o in ops or noise.CATALOGUE)
    noisy = SPARK.bind("tokens", tokens, lambda _: f"case op_id {chosen} end")
    return drawn.withColumn("noisy", F.expr(f"case when op_id is not null then {noisy} end")).select(*df.columns, *keep, "op_id", "noisy")


def with_sketch(df: DataFrame, text: str = "formula", shapes: DataFrame | None = None) -> DataFrame:
    """df with sketch and sketch_key as lexing.with_sketch gives them."""
    shapes = known(df, text) if shapes is None else shapes
    rows = df.withColumn("shape", shape(text)).join(shapes.select("shape", "shape_sketch", "kinds"), "shape", "left")
    own = SPARK.bind("tokens", lexing.lex(SPARK, text), lambda _: lexing.sketch(SPARK, "tokens", "kinds"))
    # a sketch with a digit holds digits of the formula; a null formula is left to the expression
    sketch = F.expr(f"case when contains(shape_sketch, '0') or shape is null then {own} else shape_sketch end")
    return rows.withColumn("sketch", sketch).select(*df.columns, "sketch").withColumn("sketch_key", lexing.key128("sketch"))
