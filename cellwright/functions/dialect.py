"""Expressions over token arrays, rendered for Spark SQL or, for checking, for DuckDB.

Everything a formula method does inside one row is an expression over arrays. Rendering it twice keeps the Spark side
within Catalyst (no Python per row) and gives an engine of another make to compare with.
"""

from __future__ import annotations


class Spark:
    """Spark SQL."""

    def lit(self, s: str) -> str:
        return "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"

    def each(self, xs: str, var: str, body: str) -> str:
        return f"transform({xs}, {var} -> {body})"

    def keep(self, xs: str, var: str, body: str) -> str:
        return f"filter({xs}, {var} -> {body})"

    def some(self, xs: str, var: str, body: str) -> str:
        return f"exists({xs}, {var} -> {body})"

    def seq(self, a: str, b: str) -> str:
        return f"slice(sequence(cast({a} as int), cast(greatest({a}, {b}) as int)), 1, cast(greatest(({b}) - ({a}) + 1, 0) as int))"

    def at(self, xs: str, i: str) -> str:
        return f"get({xs}, cast({i} as int) - 1)"

    def size(self, xs: str) -> str:
        return f"size({xs})"

    def cut(self, xs: str, a: str, b: str) -> str:
        return f"slice({xs}, cast({a} as int), cast(greatest(({b}) - ({a}) + 1, 0) as int))"

    def cat(self, *xs: str) -> str:
        return f"concat({', '.join(xs)})"

    def arr(self, *xs: str) -> str:
        return f"array({', '.join(xs)})"

    def join(self, xs: str) -> str:
        return f"array_join({xs}, '')"

    def rx_all(self, s: str, p: str) -> str:
        return f"regexp_extract_all({s}, {self.lit(p)}, 0)"

    def rx(self, s: str, p: str) -> str:
        return f"({s} rlike {self.lit(p)})"

    def rx_cut(self, s: str, p: str, to: str) -> str:
        return f"regexp_replace({s}, {self.lit(p)}, {self.lit(to)})"

    def u32(self, *parts: str) -> str:
        return f"cast(conv(substr(md5(concat_ws('|', {', '.join(f'cast({p} as string)' for p in parts)})), 1, 8), 16, 10) as bigint)"

    def has(self, xs: list[str], x: str) -> str:
        return f"({x} in ({', '.join(map(self.lit, xs))}))"

    def flat(self, xs: str) -> str:
        return f"flatten({xs})"

    def chars(self, s: str) -> str:
        return f"regexp_extract_all({s}, '(?s:.)', 0)"

    def sum(self, xs: str) -> str:
        return f"aggregate({xs}, cast(0 as bigint), (acc, y) -> acc + y)"

    def most(self, xs: str) -> str:
        return f"array_max({xs})"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) div ({b}))"

    def names(self, **fields: str) -> str:
        return f"named_struct({', '.join(f'{self.lit(k)}, {v}' for k, v in fields.items())})"

    def bind(self, name: str, value: str, body) -> str:
        """body(name), with the value worked out once: written out in a lambda it would be made anew for each element."""
        return f"get(transform(array({value}), {name} -> {body(name)}), 0)"

    def bound(self, steps: list[dict[str, str]]) -> str:
        """A struct of all columns of the steps, each worked out once. As columns of their own they would not be: Catalyst
        writes a column that is read once into the expression that reads it, also into a lambda."""
        out = self.names(**{k: k for s in steps for k in s})
        for k, v in reversed([c for s in steps for c in s.items()]):
            out = self.bind(k, v, lambda _, inner=out: inner)
        return out


class Duck(Spark):
    """DuckDB."""

    def lit(self, s: str) -> str:
        return "'" + s.replace("'", "''") + "'"

    def each(self, xs: str, var: str, body: str) -> str:
        return f"list_transform({xs}, lambda {var}: {body})"

    def keep(self, xs: str, var: str, body: str) -> str:
        return f"list_filter({xs}, lambda {var}: {body})"

    def some(self, xs: str, var: str, body: str) -> str:
        return f"(len(list_filter({xs}, lambda {var}: {body})) > 0)"

    def seq(self, a: str, b: str) -> str:
        return f"range(cast({a} as bigint), cast({b} as bigint) + 1)"

    def at(self, xs: str, i: str) -> str:
        return f"list_extract({xs}, {i})"

    def size(self, xs: str) -> str:
        return f"len({xs})"

    def cut(self, xs: str, a: str, b: str) -> str:
        return f"(CASE WHEN ({b}) < ({a}) THEN list_slice({xs}, 1, 0) ELSE list_slice({xs}, {a}, {b}) END)"

    def cat(self, *xs: str) -> str:
        return "(" + " || ".join(f"({x})" for x in xs) + ")"

    def arr(self, *xs: str) -> str:
        return f"[{', '.join(xs)}]"

    def join(self, xs: str) -> str:
        return f"array_to_string({xs}, '')"

    def rx_all(self, s: str, p: str) -> str:
        return f"regexp_extract_all({s}, {self.lit(p)})"

    def rx(self, s: str, p: str) -> str:
        return f"regexp_matches({s}, {self.lit(p)})"

    def rx_cut(self, s: str, p: str, to: str) -> str:
        return f"regexp_replace({s}, {self.lit(p)}, {self.lit(to)}, 'g')"

    def u32(self, *parts: str) -> str:
        return f"cast('0x' || substr(md5(concat_ws('|', {', '.join(f'cast({p} as varchar)' for p in parts)})), 1, 8) as bigint)"

    def chars(self, s: str) -> str:
        return f"regexp_extract_all({s}, '(?s:.)')"

    def sum(self, xs: str) -> str:
        return f"cast(coalesce(list_sum({xs}), 0) as bigint)"

    def most(self, xs: str) -> str:
        return f"list_max({xs})"

    def div(self, a: str, b: str) -> str:
        return f"(({a}) // ({b}))"

    def bind(self, name: str, value: str, body) -> str:
        return body(value)

    def names(self, **fields: str) -> str:
        return "{" + ", ".join(f"{self.lit(k)}: {v}" for k, v in fields.items()) + "}"


SPARK, DUCK = Spark(), Duck()
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_upper(x: str) -> str:
    """Only A-Z: the engines' upper() differ on other letters."""
    return f"translate({x}, '{LOWER}', '{UPPER}')"
