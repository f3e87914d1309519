"""Pre-training objectives: tail masking, span masking, random noise, user noise, and the mixer that deals them to batches.

All randomness is a keyed hash of seed, row and place, so results do not depend on partitions, retries or engine.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellwright.functions import lexing, noise, shapes
from cellwright.functions.dialect import SPARK, Spark

MASK = "<mask>"
TWO32 = 1 << 32
TAIL_RATES = (30, 40, 50, 60, 70)
SPAN_GRID = ((35, 6), (35, 2), (15, 6), (15, 2))
NOISE_VOCAB = ("(", ")", ",", ":", "=", "+", "-", "*", "/", "&", "<", ">", '"', "!", "1", "0", "a1", "sum", "if", "vlookup")
#: objective: weight in percent
WEIGHTS = {"span": 50, "tail": 20, "user": 20, "random": 5, "intact": 5}
ABLATION_BASE = {"generic": 100}
ABLATION_M = {"span": 50, "tail": 20, "random": 25, "intact": 5}
ABLATION_MN = WEIGHTS
VARIANTS = {"span": [f"{r}/{n}" for r, n in SPAN_GRID], "tail": [str(r) for r in TAIL_RATES], "user": ["-"], "random": ["10"], "intact": ["-"], "generic": ["15/1-5"]}


def tail_mask(d: Spark, text: str, percent: int | str) -> str:
    """The text without its trailing percent of characters."""
    return f"substring({text}, 1, cast({d.div(f'length({text}) * (100 - ({percent}))', '100')} as int))"


def start_threshold(rate: int, mean: float) -> int:
    """Hash bound for a span to start at a place, so that the expected share of covered places is rate percent."""
    return int((1 - (1 - rate / 100) ** (1 / mean)) * TWO32)


def span_ends(d: Spark, seed: int, key: str, total: str, rate: int, mean: int, law: str = "fixed") -> str:
    """Last place of the span that starts at each place from 2 - reach to total, or the place before it where none starts.
    One draw a place. law: fixed length, geometric with that mean, or uniform from 1 to 2 mean - 1."""
    drawn = d.u32(str(seed), key, "s", "'length'")
    if law == "fixed":
        length = str(mean)
    elif law == "geometric":
        bounds = d.arr(*(f"cast({int((1 - 1 / mean) ** k * TWO32)} as bigint)" for k in range(8 * mean)))
        length = d.size(d.keep(bounds, "w", f"{drawn} < w"))
    else:
        length = f"{drawn} % {2 * mean - 1} + 1"
    start = f"{d.u32(str(seed), key, 's', "'span'")} < {start_threshold(rate, mean)}"
    return d.each(d.seq(str(2 - reach(mean, law)), total), "s", f"cast(case when {start} then s + {length} - 1 else s - 1 end as bigint)")


def reach(mean: int, law: str) -> int:
    """The longest span."""
    return {"fixed": mean, "geometric": 8 * mean, "uniform": 2 * mean - 1}[law]


def covered(d: Spark, ends: str, place: str, mean: int, law: str) -> str:
    """Whether a span covers the place: one that starts at most reach - 1 places before it ends there or later."""
    return d.some(d.cut(ends, place, f"({place}) + {reach(mean, law) - 1}"), "e", f"e >= {place}")


def _collapsed(d: Spark, units: str, masked: str) -> str:
    """Units joined, runs of masked ones as one mask; masked: array of booleans."""
    m, before = d.at(masked, "i"), f"coalesce({d.at(masked, 'i - 1')}, false)"
    return d.join(d.each(d.seq("1", d.size(units)), "i", f"case when {m} and {before} then '' when {m} then '{MASK}' else {d.at(units, 'i')} end"))


def span_columns(d: Spark, seed: int, key: str, rate: int, mean: int, law: str = "fixed") -> list[dict[str, str]]:
    """Steps over tokens, kinds: sub-token counts, first sub-token of each lexer token, span ends, what is masked, the masked text.

    A lexer token is masked whole, if its first sub-token is covered."""
    counts = d.each(lexing.model_tokens(d, "tokens", "kinds"), "x", f"cast({d.size('x')} as bigint)")
    first = d.each(d.seq("1", d.size("counts")), "i", f"1 + {d.sum(d.cut('counts', '1', 'i - 1'))}")
    return [
        {"counts": counts},
        {"firsts": first, "span_ends": span_ends(d, seed, key, d.sum("counts"), rate, mean, law)},
        {"masked": d.each("firsts", "f", covered(d, "span_ends", "f", mean, law))},
        {"span_source": _collapsed(d, "tokens", "masked")},
    ]


def generic_span_columns(d: Spark, seed: int, key: str, rate: int = 15, mean: int = 3, law: str = "uniform") -> list[dict[str, str]]:
    """As span_columns over sub-tokens, without regard to the lexer's boundaries; lengths 1 to 5."""
    return [
        {"pieces": d.flat(lexing.model_tokens(d, "tokens", "kinds"))},
        {"span_ends": span_ends(d, seed, key, d.size("pieces"), rate, mean, law)},
        {"masked": d.each(d.seq("1", d.size("pieces")), "f", covered(d, "span_ends", "f", mean, law))},
        {"span_source": _collapsed(d, "pieces", "masked")},
    ]


def random_noise(d: Spark, seed: int, key: str, rate: int = 10, vocab: tuple[str, ...] = NOISE_VOCAB) -> str:
    """Tokens inserted, deleted or replaced, each for a third of rate percent of the places."""
    bound = rate * TWO32 // 300
    h, x = d.u32(str(seed), key, "i", "'noise'"), d.at("tokens", "i")
    new = d.at(d.arr(*map(d.lit, vocab)), f"1 + {d.u32(str(seed), key, 'i', "'token'")} % {len(vocab)}")
    return d.join(d.each(d.seq("1", d.size("tokens")), "i", f"case when {h} < {bound} then concat({x}, {new}) when {h} < {2 * bound} then '' when {h} < {3 * bound} then {new} else {x} end"))


def batch_of(d: Spark, seed: int, key: str, batches: int) -> str:
    return f"({d.u32(str(seed), key, "'batch'")} % {batches})"


def objective_of(d: Spark, seed: int, weights: dict[str, int] = WEIGHTS) -> str:
    """Objective of a batch (column batch_id), by cumulative weights."""
    if sum(weights.values()) != 100:
        raise ValueError("weights must sum to 100")
    h, total, out = f"{d.u32(str(seed), 'batch_id', "'objective'")} % 100", 0, []
    for name, w in weights.items():
        total += w
        out.append(f"when {h} < {total} then '{name}'")
    return "case " + " ".join(out) + " end"


def variant_of(d: Spark, seed: int) -> str:
    """Variant of a batch within its objective, uniform."""
    h = d.u32(str(seed), "batch_id", "'variant'")
    return "case objective " + " ".join(f"when '{o}' then {d.at(d.arr(*map(d.lit, v)), f'1 + {h} % {len(v)}')}" for o, v in VARIANTS.items()) + " end"


def assign_objectives(df: DataFrame, batches: int, seed: int, weights: dict[str, int] = WEIGHTS, key: str = "formula_id") -> DataFrame:
    """Adds batch_id, objective, variant: one objective for each batch. A batch is a hash bucket, so there is no sort."""
    out = df.withColumn("batch_id", F.expr(batch_of(SPARK, seed, key, batches)))
    return out.withColumn("objective", F.expr(objective_of(SPARK, seed, weights))).withColumn("variant", F.expr(variant_of(SPARK, seed)))


def span_mask(df: DataFrame, rate: int, mean: int, seed: int = 1, law: str = "fixed", boundary: str = "lexer", key: str = "formula_id") -> DataFrame:
    """Adds source (masked text) and masked to a table with tokens, kinds."""
    steps = span_columns(SPARK, seed, key, rate, mean, law) if boundary == "lexer" else generic_span_columns(SPARK, seed, key, rate, mean, law)
    return lexing.with_steps(df, steps, [c for s in steps for c in s]).withColumnRenamed("span_source", "source")


def pretraining_pairs(df: DataFrame, batches: int, seed: int | str = 1, weights: dict[str, int] = WEIGHTS, key: str = "formula_id", text: str = "formula", more: tuple[str, ...] = (), only: tuple[str, ...] | None = None, known: DataFrame | None = None) -> DataFrame:
    """key, batch_id, objective, variant, source, target. Every objective's target is the whole formula. seed: a number, or
    a column of df; more: columns of df to keep; only: the objectives whose rows are wanted, dealt as if all were; known:
    shapes.known of a table that has these texts, where it is at hand.

    Objectives are applied to their own rows only: a filter for each, then one expression, then a union."""
    dealt = assign_objectives(lexing.with_tokens(df.select(key, text, *more), text), batches, seed, weights, key)
    out = []
    for name in (w for w in weights if only is None or w in only):
        rows = dealt.where(F.col("objective") == name)
        if name == "span":
            for r, n in SPAN_GRID:
                out.append(span_mask(rows.where(F.col("variant") == f"{r}/{n}"), r, n, seed, key=key))
        elif name == "generic":
            out.append(span_mask(rows, 15, 3, seed, "uniform", "none", key))
        elif name == "tail":
            out.append(rows.withColumn("source", F.expr(tail_mask(SPARK, text, "cast(variant as int)"))))
        elif name == "user":
            noisy = noise.user_noise(rows, seed, key) if known is None else shapes.with_noise(rows.drop("tokens", "kinds"), seed, key, text=text, shapes=known)
            out.append(noisy.withColumn("source", F.coalesce("noisy", text)))
        elif name == "random":
            out.append(rows.withColumn("source", F.expr(random_noise(SPARK, seed, key))))
        else:
            out.append(rows.withColumn("source", F.col(text)))
    parts = [o.select(key, *more, "batch_id", "objective", "variant", "source", F.col(text).alias("target")) for o in out]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.unionByName(p)
    return whole


def _span_source(seed: str, key: str, text: str) -> str:
    """As span_columns with law fixed, from columns firsts and total of the shape, span_mean and span_bound of the batch.
    A draw is compared as the eight hexadecimal digits that it is."""
    d = SPARK
    drawn = f"substr(md5(concat_ws('|', cast({seed} as string), cast({key} as string), cast(s as string), 'span')), 1, 8)"
    ends = d.each(d.seq("2 - span_mean", "total"), "s", f"case when {drawn} < span_bound then s + span_mean - 1 else s - 1 end")
    masked = d.each("firsts", "f", d.some("slice(ends, cast(f as int), span_mean)", "e", "e >= f"))
    return d.bind("tokens", lexing.lex(d, text), lambda _: d.bind("ends", ends, lambda _: d.bind("masked", masked, lambda _: _collapsed(d, "tokens", "masked"))))


def pretraining_stream(df: DataFrame, batches: int, epochs: int = 10, weights: dict[str, int] = WEIGHTS, key: str = "formula_id", known: DataFrame | None = None) -> DataFrame:
    """Curated formulas as training pairs of several epochs: epoch, batch_id, objective, variant, source, target.

    Each formula is read once an epoch; the epoch is the seed, so it meets other batches, objectives and masks in each. df:
    deduplicated formulas. One plan whatever the number of epochs: rows are multiplied, not queries.

    Objective and variant are looked up, one row a batch and epoch, and all objectives are applied in one pass; what depends
    on the tokens' places alone is made once a shape. known: shapes.known of a table that has these texts."""
    if not set(weights) <= {"span", "tail", "user", "random", "intact"}:
        rows = df.select(key, "formula", F.explode(F.sequence(F.lit(1), F.lit(epochs))).alias("epoch"))
        return pretraining_pairs(rows, batches, "epoch", weights, key, more=("epoch",))
    known = shapes.known(df) if known is None else known
    dealt = df.sparkSession.range(batches).select(F.col("id").alias("batch_id"), F.explode(F.sequence(F.lit(1), F.lit(epochs))).alias("epoch"))
    dealt = dealt.withColumn("objective", F.expr(objective_of(SPARK, "epoch", weights))).withColumn("variant", F.expr(variant_of(SPARK, "epoch")))
    mean = F.when(F.col("objective") == "span", F.element_at(F.split("variant", "/"), -1).cast("int"))
    bound = F.expr("case variant " + " ".join(f"when '{r}/{n}' then '{start_threshold(r, n):08x}'" for r, n in SPAN_GRID) + " end")
    dealt = dealt.withColumn("span_mean", mean).withColumn("span_bound", bound)
    rows = df.select(key, "formula", F.explode(F.sequence(F.lit(1), F.lit(epochs))).alias("epoch")).withColumn("batch_id", F.expr(batch_of(SPARK, "epoch", key, batches)))
    rows = rows.join(F.broadcast(dealt), ["epoch", "batch_id"])  # batches x epochs rows
    rows = shapes.with_noise(rows, "epoch", key, shapes=known, on="objective = 'user'", keep=("firsts", "total"))
    random = SPARK.bind("tokens", lexing.lex(SPARK, "formula"), lambda _: random_noise(SPARK, "epoch", key))
    source = f"""case objective when 'span' then {_span_source("epoch", key, "formula")} when 'tail' then {tail_mask(SPARK, "formula", "cast(variant as int)")}
        when 'user' then coalesce(noisy, formula) when 'random' then {random} else formula end"""
    return rows.select(key, "epoch", "batch_id", "objective", "variant", F.expr(source).alias("source"), F.col("formula").alias("target"))


def corruption_audit(pairs: DataFrame, key: str = "formula_id") -> DataFrame:
    """Of each objective and variant: pairs, runs of masks, characters hidden, pieces between masks that are no whole tokens of
    the formula (none for lexer spans), and batches that hold more than one objective (none)."""
    pieces = f"flatten(transform(split(source, '{MASK}', -1), p -> {lexing.lex(SPARK, 'p')}))"
    broken = F.expr(f"exists({pieces}, x -> x <> '' and not array_contains({lexing.lex(SPARK, 'target')}, x))")
    lone = pairs.groupBy("batch_id").agg(F.countDistinct("objective", "variant").alias("kinds"))
    rows = pairs.join(lone, "batch_id")
    masked = F.col("objective").isin("span", "generic")
    runs = (F.length("source") - F.length(F.replace("source", F.lit(MASK), F.lit("")))) / len(MASK)
    left = F.length(F.replace("source", F.lit(MASK), F.lit("")))
    return rows.groupBy("objective", "variant").agg(
        F.count(F.lit(1)).alias("n"),
        F.sum(runs.cast("long")).alias("runs"),
        F.round(F.sum(F.length("target") - left) / F.sum(F.length("target")), 6).alias("hidden"),
        F.sum(F.when(masked, broken.cast("long")).otherwise(F.lit(0))).alias("broken"),
        F.sum((F.col("kinds") > 1).cast("long")).alias("mixed"),
    )


def corruption_report(pairs: DataFrame) -> DataFrame:
    """Of each objective and variant: rows, batches, masks a row, share unchanged, mean lengths."""
    masks = (F.length("source") - F.length(F.replace("source", F.lit(MASK), F.lit("")))) / len(MASK)
    return pairs.groupBy("objective", "variant").agg(
        F.count(F.lit(1)).alias("n"),
        F.countDistinct("batch_id").alias("batches"),
        F.round(F.avg(masks), 6).alias("masks"),
        F.round(F.avg((F.col("source") == F.col("target")).cast("int")), 6).alias("unchanged"),
        F.round(F.avg(F.length("source") / F.length("target")), 6).alias("length_ratio"),
    )
