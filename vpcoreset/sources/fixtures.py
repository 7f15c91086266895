"""The given tables as vertical datasets. A party is one SELECT, so that it reads its own columns and no others."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


@dataclass(frozen=True)
class Fixture:
    """parties: (features, SELECT of id, features and, at the last one, label); the SELECTs read both engines' SQL."""

    parties: tuple[tuple[tuple[str, ...], str], ...]
    label: str | None = None
    weight: str | None = None


def _count(text: str, members: str) -> str:
    return f"CAST(length({text}) - length(translate({text}, {members}, '')) AS DOUBLE)"


_DIGITS, _UPPER, _PUNCT = "'0123456789'", "'ABCDEFGHIJKLMNOPQRSTUVWXYZ'", "'!#$%&()*+,-/:;<=>?@[]^_{{|}}~'"
_LINE_KEY = "HEX15(l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice)"


def _docs() -> Fixture:
    return Fixture((
        (("digits", "upper"), f"SELECT doc_id AS id, {_count('text', _DIGITS)} AS digits, {_count('text', _UPPER)} AS upper FROM {{documents}}"),
        (("dots", "lines"), f"SELECT doc_id AS id, {_count('text', chr(39) + '.' + chr(39))} AS dots, {_count('text', 'chr(10)')} AS lines FROM {{documents}}"),
        (("punct", "is_en"), f"SELECT doc_id AS id, {_count('text', _PUNCT)} AS punct, CAST(CASE WHEN lang = 'en' THEN 1 ELSE 0 END AS DOUBLE) AS is_en, CAST(n_chars AS DOUBLE) AS y FROM {{documents}}"),
    ), "y")


def _docs3() -> Fixture:
    """One column a party, so that closed forms stay short."""
    (_, a), (_, b), (_, c) = _docs().parties
    return Fixture(((("digits",), a), (("dots",), b), (("punct",), c)), "y")


def _docs_quality() -> Fixture:
    d = _docs()
    last = d.parties[2]
    return Fixture((*d.parties[:2], (last[0], last[1].replace("CAST(n_chars AS DOUBLE) AS y FROM {documents}", "CAST(quality AS DOUBLE) AS y FROM {documents} JOIN {labels} USING (doc_id)"))), "y")


def _line(label: str, extra: str = "", planted: bool = False) -> Fixture:
    part = " JOIN {part} ON l_partkey = p_partkey" if planted else ""
    return Fixture((
        (("qty", "disc", "tax"), f"SELECT {_LINE_KEY} AS id, l_quantity AS qty, l_discount AS disc, l_tax AS tax{extra} FROM {{lineitem}}"),
        (("p_size", "p_price"), f"SELECT {_LINE_KEY} AS id, CAST(p_size AS DOUBLE) AS p_size, p_retailprice AS p_price FROM {{lineitem}} JOIN {{part}} ON l_partkey = p_partkey"),
        (("o_total", "s_bal", "c_bal"), f"SELECT {_LINE_KEY} AS id, o_totalprice AS o_total, s_acctbal AS s_bal, c_acctbal AS c_bal, {label} AS y FROM {{lineitem}} JOIN {{orders}} ON l_orderkey = o_orderkey JOIN {{supplier}} ON l_suppkey = s_suppkey JOIN {{customer}} ON o_custkey = c_custkey{part}"),
    ), "y")


#: Coefficients of the planted label, for columns over their usual size.
PLANTED = (("l_quantity / 50", 1.0), ("l_discount / 0.1", -2.0), ("l_tax / 0.08", 0.5), ("p_size / 50.0", 1.5), ("p_retailprice / 2000", -1.0), ("o_totalprice / 500000", 2.0), ("s_acctbal / 10000", 0.3), ("c_acctbal / 10000", -0.7))


def _line_planted() -> Fixture:
    """A label of known coefficients and a noise of a hash of the key, at most 0.01 to either side."""
    noise = "HEX15(l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) / 1152921504606846976e0 * 0.02 - 0.01"
    return _line(" + ".join(f"({c}) * ({t})" for c, t in PLANTED) + f" + {noise}", planted=True)


def _line_rev() -> Fixture:
    f = _line("l_extendedprice * (1 - l_discount) * (1 + l_tax)", ", l_extendedprice AS price")
    (names, sql), *rest = f.parties
    return Fixture((((*names, "price"), sql), *rest), "y")


def _vector(widths: tuple[int, ...]) -> Fixture:
    parties, at = [], 0
    for j, w in enumerate(widths):
        names = tuple(f"e{i}" for i in range(at, at + w))
        cols = ", ".join(f"CAST(ELEMENT(embedding, {i + 1}) AS DOUBLE) AS e{i}" for i in range(at, at + w))
        parties.append((names, f"SELECT vec_id AS id, {cols}{', CAST(label AS DOUBLE) AS y' if j == len(widths) - 1 else ''} FROM {{embeddings}}"))
        at += w
    return Fixture(tuple(parties), "y")


_TYPES = ("click", "error", "purchase", "signup", "view")


def _events() -> Fixture:
    hot = ", ".join(f"CAST(CASE WHEN event_type = '{t}' THEN 1 ELSE 0 END AS DOUBLE) AS is_{t}" for t in _TYPES[:4])
    return Fixture((
        (("second", "k"), "SELECT event_id AS id, CAST(hour(ts) * 3600 + minute(ts) * 60 + floor(second(ts)) AS DOUBLE) AS second, CAST(JSONK(props) AS DOUBLE) AS k FROM {events}"),
        (tuple(f"is_{t}" for t in _TYPES[:4]), f"SELECT event_id AS id, {hot} FROM {{events}}"),
        (("week_hour",), "SELECT event_id AS id, CAST((DOW(ts)) * 24 + hour(ts) AS DOUBLE) AS week_hour, value AS y FROM {events}"),
    ), "y")


def _pages() -> Fixture:
    return Fixture((
        (("url_len", "slashes"), f"SELECT page_id AS id, CAST(length(url) AS DOUBLE) AS url_len, {_count('url', chr(39) + '/' + chr(39))} AS slashes FROM {{pages}}"),
        (("html_len", "tags"), f"SELECT page_id AS id, CAST(length(html) AS DOUBLE) AS html_len, {_count('html', chr(39) + '<' + chr(39))} AS tags FROM {{pages}}"),
        (("quotes", "digits"), f"SELECT page_id AS id, {_count('html', chr(39) + '=' + chr(39))} AS quotes, {_count('html', _DIGITS)} AS digits, {_count('html', _UPPER)} AS y FROM {{pages}}"),
    ), "y")


def _conversations() -> Fixture:
    return Fixture((
        (("turn", "is_user"), "SELECT conv_id * 1000 + turn AS id, CAST(turn AS DOUBLE) AS turn, CAST(CASE WHEN role = 'user' THEN 1 ELSE 0 END AS DOUBLE) AS is_user FROM {conversations}"),
        (("words", "digits"), f"SELECT conv_id * 1000 + turn AS id, {_count('text', chr(39) + ' ' + chr(39))} + 1 AS words, {_count('text', _DIGITS)} AS digits, CAST(length(text) AS DOUBLE) AS y FROM {{conversations}}"),
    ), "y")


FIXTURES = {
    "docs": _docs(), "docs3": _docs3(), "docs_quality": _docs_quality(), "line_star": _line("l_extendedprice"), "line_rev": _line_rev(), "line_planted": _line_planted(),
    "emb3": _vector((22, 21, 21)), "emb4": _vector((16, 16, 16, 16)), "emb2": _vector((48, 16)), "emb8": _vector((8,) * 8),
    "ev": _events(), "pages": _pages(), "conv": _conversations(),
}

_WORDS = {  # spelling of what the engines name differently: (Spark, DuckDB)
    "ELEMENT(": ("element_at(", "list_extract("),
    "JSONK(props)": ("get_json_object(props, '$.k')", "json_extract_string(props, '$.k')"),
    "DOW(ts)": ("dayofweek(ts) - 1", "dayofweek(ts)"),
}


def _hex15(sql: str, duck: bool) -> str:
    while "HEX15(" in sql:
        head, _, tail = sql.partition("HEX15(")
        inside, _, rest = tail.partition(")")
        text = f"md5(concat_ws(':', {inside}))"
        sql = head + (f"CAST('0x' || substr({text}, 1, 15) AS BIGINT)" if duck else f"CAST(conv(substr({text}, 1, 15), 16, 10) AS BIGINT)") + rest
    return sql


def engine_sql(sql: str, duck: bool) -> str:
    for word, spelled in _WORDS.items():
        sql = sql.replace(word, spelled[duck])
    sql = _hex15(sql, duck)
    return sql.format(**{t: t for t in TABLES}) if duck else sql


def read(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    """A SELECT over {table} names on the files of a folder."""
    used = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES if "{" + t + "}" in sql}
    return spark.sql(engine_sql(sql, False), **used)


def wide_sql(name: str) -> str:
    """DuckDB SELECT of id, all features and label of a fixture."""
    f = FIXTURES[name]
    parts = [f"({engine_sql(sql, True)}) p{j}" for j, (_, sql) in enumerate(f.parties)]
    cols = ", ".join([f"p{j}.{c}" for j, (names, _) in enumerate(f.parties) for c in names] + ([f"p{len(parts) - 1}.{f.label}"] if f.label else []))
    return f"SELECT p0.id, {cols} FROM {parts[0]} " + " ".join(f"JOIN {p} ON p{j}.id = p0.id" for j, p in list(enumerate(parts))[1:])
