"""Text expressions that DuckDB can repeat: tokens, names, n-grams, digests."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Shortened words in names, and what they stand for. Fixed values.
ABBREVIATIONS = {
    "acctbal": "account balance", "addr": "address", "amt": "amount", "cd": "code", "chars": "characters", "conv": "conversation", "crs": "course", "cust": "customer",
    "custkey": "customer key", "dept": "department", "desc": "description", "did": "department id", "doc": "document", "extendedprice": "extended price", "cid": "course id", "id": "identifier",
    "lang": "language", "linenumber": "line number", "linestatus": "line status", "mktsegment": "market segment", "n": "number of", "nationkey": "nation key", "nm": "name", "no": "number",
    "num": "number", "orderdate": "order date", "orderkey": "order key", "orderpriority": "order priority", "orderstatus": "order status", "partkey": "part key", "props": "properties", "qty": "quantity",
    "regionkey": "region key", "retailprice": "retail price", "returnflag": "return flag", "shipdate": "ship date", "std": "student", "suppkey": "supplier key", "totalprice": "total price", "ts": "timestamp",
    "vec": "vector",
}
STOP = ["a", "an", "and", "are", "by", "do", "does", "each", "for", "from", "has", "have", "how", "in", "is", "it", "of", "on", "or", "per", "than", "that", "the", "there", "to", "was", "were", "what", "which", "with"]


def tokens(text: Column | str) -> Column:
    """Lower-case runs of ASCII letters and digits, in order."""
    return F.filter(F.split(F.lower(text if isinstance(text, Column) else F.col(text)), "[^a-z0-9]+"), lambda t: t != "")


def tokens_sql(text: str) -> str:
    return f"list_filter(string_split_regex(lower({text}), '[^a-z0-9]+'), lambda t: t <> '')"


def bare_name(name: Column | str) -> Column:
    """A column name without a one-letter table prefix."""
    return F.regexp_replace(F.lower(name if isinstance(name, Column) else F.col(name)), "^[a-z]_", "")


def bare_name_sql(name: str) -> str:
    return f"regexp_replace(lower({name}), '^[a-z]_', '')"


def expanded(name: Column | str) -> Column:
    """Words of a name, shortened ones written out."""
    table = F.create_map(*(F.lit(x) for kv in ABBREVIATIONS.items() for x in kv))
    return F.array_join(F.transform(F.split(bare_name(name), "_"), lambda w: F.coalesce(F.element_at(table, w), w)), " ")


def expanded_sql(name: str) -> str:
    keys, values = ", ".join(f"'{k}'" for k in ABBREVIATIONS), ", ".join(f"'{v}'" for v in ABBREVIATIONS.values())
    return f"array_to_string(list_transform(string_split({bare_name_sql(name)}, '_'), lambda w: coalesce(map([{keys}], [{values}])[w], w)), ' ')"


def grams(text: Column, n: int = 3) -> Column:
    """Distinct character n-grams; empty for shorter texts."""
    return F.when(F.length(text) >= n, F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(text) - n + 1, F.lit(1))), lambda i: F.substring(text, i, F.lit(n))))).otherwise(F.array().cast("array<string>"))


def grams_sql(text: str, n: int = 3) -> str:
    return f"CASE WHEN length({text}) >= {n} THEN list_distinct(list_transform(generate_series(1, length({text}) - {n - 1}), lambda i: substr({text}, CAST(i AS INTEGER), {n}))) ELSE CAST([] AS VARCHAR[]) END"


def jaccard(a: Column, b: Column) -> Column:
    both = F.size(F.array_intersect(a, b))
    return F.coalesce(both / F.nullif(F.size(F.array_union(a, b)), F.lit(0)), F.lit(0.0))


def jaccard_sql(a: str, b: str) -> str:
    return f"coalesce(len(list_intersect({a}, {b})) / nullif(CAST(len(list_distinct(list_concat({a}, {b}))) AS DOUBLE), 0), 0.0)"


def digest(*parts: Column | str) -> Column:
    """The first 32 bits of an md5, which DuckDB can form too."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *(p if isinstance(p, Column) else F.lit(p) for p in parts))), 1, 8), 16, 10).cast("long")


def digest_sql(*parts: str) -> str:
    return f"CAST('0x' || substr(md5({" || '|' || ".join(parts)}), 1, 8) AS BIGINT)"


def word_pieces(text: Column) -> Column:
    """Prompt tokens: runs of letters or digits of up to six characters, and single signs."""
    return F.regexp_count(text, F.lit(r"[A-Za-z0-9]{1,6}|[^A-Za-z0-9\s]")).cast("long")


def word_pieces_sql(text: str) -> str:
    return f"CAST(len(regexp_extract_all({text}, '[A-Za-z0-9]{{1,6}}|[^A-Za-z0-9\\s]')) AS BIGINT)"
