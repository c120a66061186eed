"""Expressions written once and expanded for Spark or for the SQL twin's engine.

H(x): first 8 hex digits of md5 as an integer. DEC(x): money with two digits as text.
TOK(x): words of letters and digits in lower case. STR(x): text. LIST(x...): array.
MAP(v, a, e): e for each v in array a. JOIN(a): array joined by spaces.
"""

from __future__ import annotations

from collections.abc import Callable

SPARK: dict[str, Callable] = {
    "H": lambda x: f"cast(conv(substr(md5({x}), 1, 8), 16, 10) as bigint)",
    "DEC": lambda x: f"cast(cast({x} as decimal(18,2)) as string)",
    "TOK": lambda x: f"filter(split(lower({x}), '[^\\\\p{{L}}\\\\p{{N}}]+'), w_ -> w_ <> '')",
    "STR": lambda x: f"cast({x} as string)",
    "MAP": lambda v, a, e: f"transform({a}, {v} -> {e})",
    "KEEP": lambda v, a, e: f"filter({a}, {v} -> {e})",
    "JOIN": lambda a: f"array_join({a}, ' ')",
    "DIV": lambda a, b: f"(({a}) div ({b}))",
    "DAY": lambda x: f"date_format({x}, 'yyyy-MM-dd')",
    "MONTH": lambda x: f"date_format({x}, 'yyyy-MM')",
    "YEAR": lambda x: f"date_format({x}, 'yyyy')",
    "SHIFT": lambda x, n: f"date_add(cast({x} as date), cast({n} as int))",
    "HEAD": lambda a, n: f"slice({a}, 1, {n})",
    "TAIL": lambda a, n: f"slice({a}, greatest(size({a}) - {n} + 1, 1), {n})",
    "FROM": lambda a, i, n: f"slice({a}, {i}, {n})",
    "COMMON": lambda a, b: f"size(array_intersect({a}, {b}))",
    "EITHER": lambda a, b: f"size(array_union({a}, {b}))",
    "LEN": lambda a: f"size({a})",
    "RX": lambda x, p, r: f"regexp_replace({x}, {p}, {r})",
    "EX": lambda x, p: f"regexp_extract({x}, {p}, 1)",
    "AT": lambda a, i: f"get({a}, ({i}) - 1)",
    "IDX": lambda v, i, a, e: f"transform({a}, ({v}, {i}0) -> {e.replace('$' + i, f'({i}0 + 1)')})",
    "NUM": lambda w: f"({w} rlike '[0-9]')",
    "KEEPI": lambda v, i, a, c: f"filter({a}, ({v}, {i}) -> {c.replace('$' + i, f'({i} + 1)')})",
    "SORTED": lambda x: f"array_sort(collect_list({x}))",
    "GRAMS": lambda a, n: f"if(size({a}) >= {n}, transform(sequence(1, size({a}) - {n} + 1), g_ -> array_join(slice({a}, g_, {n}), ' ')), array())",
    "DISTINCT": lambda a: f"array_distinct({a})",
    "LN6": lambda x: f"cast(round(ln({x}) * 1000000) as bigint)",
    "DBL": lambda x: f"cast({x} as double)",
    "BIG": lambda x: f"cast({x} as bigint)",
    "INT": lambda x: f"cast({x} as int)",
    "BITS": lambda x: f"conv(substr(md5({x}), 1, 15), 16, 10)",
    "NIB": lambda x, j: f"cast(conv(substr({x}, {j} + 1, 1), 16, 10) as int)",
}
DUCK: dict[str, Callable] = {
    "H": lambda x: f"('0x' || substr(md5({x}), 1, 8))::bigint",
    "DEC": lambda x: f"(({x})::decimal(18,2))::varchar",
    "TOK": lambda x: f"list_filter(string_split_regex(lower({x}), '[^\\p{{L}}\\p{{N}}]+'), lambda w_: w_ <> '')",
    "STR": lambda x: f"({x})::varchar",
    "MAP": lambda v, a, e: f"list_transform({a}, lambda {v}: {e})",
    "KEEP": lambda v, a, e: f"list_filter({a}, lambda {v}: {e})",
    "JOIN": lambda a: f"array_to_string({a}, ' ')",
    "DIV": lambda a, b: f"(({a}) // ({b}))",
    "DAY": lambda x: f"strftime({x}, '%Y-%m-%d')",
    "MONTH": lambda x: f"strftime({x}, '%Y-%m')",
    "YEAR": lambda x: f"strftime({x}, '%Y')",
    "SHIFT": lambda x, n: f"(({x})::date + ({n})::int)",
    "HEAD": lambda a, n: f"({a})[1:{n}]",
    "TAIL": lambda a, n: f"({a})[greatest(len({a}) - {n} + 1, 1):]",
    "FROM": lambda a, i, n: f"({a})[{i}:({i}) + ({n}) - 1]",
    "COMMON": lambda a, b: f"len(list_distinct(list_intersect({a}, {b})))",
    "EITHER": lambda a, b: f"len(list_distinct(list_concat({a}, {b})))",
    "LEN": lambda a: f"len({a})",
    "RX": lambda x, p, r: f"regexp_replace({x}, {p}, {r}, 'g')",
    "EX": lambda x, p: f"regexp_extract({x}, {p}, 1)",
    "AT": lambda a, i: f"({a})[{i}]",
    "IDX": lambda v, i, a, e: f"list_transform({a}, lambda {v}, {i}0: {e.replace('$' + i, f'{i}0')})",
    "NUM": lambda w: f"regexp_matches({w}, '[0-9]')",
    "KEEPI": lambda v, i, a, c: f"list_filter({a}, lambda {v}, {i}: {c.replace('$' + i, i)})",
    "SORTED": lambda x: f"list_sort(list({x}))",
    "GRAMS": lambda a, n: f"list_transform(range(1, greatest(len({a}) - {n} + 2, 1)), lambda g_: array_to_string(({a})[g_:g_ + {n} - 1], ' '))",
    "DISTINCT": lambda a: f"list_distinct({a})",
    "LN6": lambda x: f"round(ln({x}) * 1000000)::bigint",
    "DBL": lambda x: f"({x})::double",
    "BIG": lambda x: f"({x})::bigint",
    "INT": lambda x: f"({x})::int",
    "NIB": lambda x, j: f"('0x' || substr({x}, {j} + 1, 1))::int",
}


def _arguments(text: str, at: int) -> tuple[list[str], int]:
    """Arguments of the call whose bracket opens at `at`, and where it ends."""
    depth, quote, out, begin = 0, False, [], at + 1
    for i in range(at, len(text)):
        c = text[i]
        if c == "'":
            quote = not quote
        if quote:
            continue
        if c in "([":
            depth += 1
        elif c in ")]":
            depth -= 1
            if not depth:
                return [*out, text[begin:i].strip()], i + 1
        elif c == "," and depth == 1:
            out.append(text[begin:i].strip())
            begin = i + 1
    raise ValueError(f"unclosed bracket in {text[at:at + 60]}")


def expand(text: str, rules: dict[str, Callable]) -> str:
    out, i = "", 0
    while i < len(text):
        if text[i] == "'":
            j = text.index("'", i + 1) + 1
            out, i = out + text[i:j], j
            continue
        if text[i].isalpha() or text[i] == "_":
            j = i
            while j < len(text) and (text[j].isalnum() or text[j] == "_"):
                j += 1
            word = text[i:j]
            if j < len(text) and text[j] == "(" and word in rules:
                args, i = _arguments(text, j)
                out += rules[word](*[expand(a, rules) for a in args])
                continue
            out, i = out + word, j
            continue
        out, i = out + text[i], i + 1
    return out


def spark_sql(text: str) -> str:
    return expand(text, SPARK)


def duck_sql(text: str) -> str:
    return expand(text, DUCK)
