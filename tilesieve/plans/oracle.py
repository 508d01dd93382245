"""Pieces of oracle SQL (DuckDB): the same steps as the operators, over plain relations."""

from __future__ import annotations

import math

from tilesieve.functions.sizing import BUCKET_BITS, plan_filter

BLANKS = r"[ \t\n\r\f]+"
K = plan_filter(10_000).k


def norm(c: str) -> str:
    return f"trim(regexp_replace({c}, '{BLANKS}', ' ', 'g'))"


def src(name: str, table: str, key: str, text: str = "text", where: str = "true") -> str:
    return f"{name} AS (SELECT {key}, {norm(text)} AS text FROM {table} WHERE {where})"


def tiles(name: str, of: str, key: str, n: int = 50) -> str:
    return f"{name} AS (SELECT {key}, i::INT AS tile_no, substr(text, i * {n} + 1, {n}) AS gram FROM (SELECT {key}, text, unnest(range(0, length(text) // {n})) AS i FROM {of}))"


def windows(name: str, of: str, key: str, n: int = 50) -> str:
    return f"{name} AS (SELECT {key}, i::INT AS pos, substr(text, i + 1, {n}) AS gram FROM (SELECT {key}, text, unnest(range(0, length(text) - {n} + 1)) AS i FROM {of}))"


def tokens(c: str) -> str:
    return rf"regexp_extract_all({c}, '[^ \t\n\r\f]+')"


def token_grams(name: str, of: str, key: str, n: int, stride: int) -> str:
    return f"{name} AS (SELECT {key}, (i // {stride})::INT AS tile_no, array_to_string(w[i + 1 : i + {n}], chr(31)) AS gram FROM (SELECT {key}, w, unnest(range(0, len(w) - {n} + 1, {stride})) AS i FROM (SELECT {key}, {tokens('text')} AS w FROM {of})))"


def spec(name: str, of: str, fpp: float = 1e-3) -> str:
    per = -math.log(fpp) / math.log(2) ** 2
    return f"{name} AS (SELECT ({BUCKET_BITS} * greatest(1, ceil(greatest(1, count(*)) * {per!r} / {BUCKET_BITS})))::BIGINT AS m FROM {of})"


def lane(gram: str, at: int) -> str:
    return f"('0x' || substr(md5({gram}), {at}, 15))::BIGINT"


def places(of: str, cols: str, spec_: str, layout: str = "classic", k: int = K) -> str:
    """A relation of ``cols`` and p, a row for each bit of each gram."""
    hashed = f"(SELECT {cols}, {lane('gram', 1)} AS h1, {lane('gram', 17)} AS h2, m FROM {of}, {spec_})"
    if layout == "blocked":
        b = BUCKET_BITS
        return f"(SELECT {cols}, (h1 % (m // {b})) * {b} + ((h2 % {b}) + j * (((h1 // (m // {b})) % {b}) | 1)) % {b} AS p FROM {hashed}, range({k}) r(j))"
    return f"(SELECT {cols}, ((h1 % m) + j * (h2 % m)) % m AS p FROM {hashed}, range({k}) r(j))"


def bits(name: str, of: str, spec_: str, layout: str = "classic", k: int = K) -> str:
    return f"{name} AS (SELECT DISTINCT p FROM {places(of, 'gram', spec_, layout, k)})"


def hits(name: str, of: str, key: str, bits_: str, spec_: str, layout: str = "classic", k: int = K) -> str:
    return f"{name} AS (SELECT {key}, pos, bool_and(b.p IS NOT NULL) AS hit FROM {places(of, f'{key}, pos', spec_, layout, k)} w LEFT JOIN {bits_} b ON w.p = b.p GROUP BY {key}, pos)"


def exact_hits(name: str, of: str, key: str, tiles_: str) -> str:
    return f"{name} AS (SELECT {key}, pos, gram IN (SELECT gram FROM {tiles_}) AS hit FROM {of})"


def chains(name: str, of: str, key: str, n: int = 50) -> str:
    return f"{name} AS (SELECT {key}, min(pos)::INT AS start, count(*) AS n_tiles, count(*) * {n} AS n_chars FROM (SELECT {key}, pos, pos % {n} AS lane, pos - {n} * row_number() OVER (PARTITION BY {key}, pos % {n} ORDER BY pos) AS isl FROM {of} WHERE hit) GROUP BY {key}, lane, isl)"


def best(name: str, docs: str, chains_: str, key: str) -> str:
    return f"{name} AS (SELECT d.{key}, coalesce(c.n_tiles, 0)::BIGINT AS max_tiles, coalesce(c.n_chars, 0)::BIGINT AS lcs_chars, c.start::BIGINT AS start FROM {docs} d LEFT JOIN (SELECT * FROM {chains_} QUALIFY row_number() OVER (PARTITION BY {key} ORDER BY n_tiles DESC, start) = 1) c USING ({key}))"


def corpus(fpp: float = 1e-3, n: int = 50, layout: str = "classic", table: str = "documents", key: str = "doc_id", text: str = "text", where: str = "true", p: str = "", k: int = K) -> str:
    """src, tiles, spec and bits of a corpus, named with the prefix ``p``."""
    return ", ".join((src(f"{p}src", table, key, text, where), tiles(f"{p}tiles", f"{p}src", key, n), spec(f"{p}spec", f"{p}tiles", fpp), bits(f"{p}bits", f"{p}tiles", f"{p}spec", layout, k)))


def asked(table: str, key: str, text: str = "text", n: int = 50, layout: str = "classic", q: str = "q", p: str = "", where: str = "true") -> str:
    """q, its windows, hits, chains and longest chains against the corpus with the prefix ``p``."""
    return ", ".join((src(q, table, key, text, where), windows(f"{q}win", q, key, n), hits(f"{q}hits", f"{q}win", key, f"{p}bits", f"{p}spec", layout), chains(f"{q}ch", f"{q}hits", key, n), best(f"{q}best", q, f"{q}ch", key)))


def eo(table: str, best_: str, key: str, group: str, n: int = 50, least: int = 1) -> str:
    """Expected overlap of each group, and of all with a null group."""
    return f"SELECT {group}, count(*) AS instances, sum(CASE WHEN max_tiles >= {least} THEN max_tiles ELSE 0 END)::BIGINT AS sum_max, round(sum(greatest(0.0, (coalesce(length(text), 0) - {n} + 1) / {n}.0)), 4)::DOUBLE AS sum_expected, round(100.0 * sum(CASE WHEN max_tiles >= {least} THEN max_tiles ELSE 0 END)::DOUBLE / nullif(sum(greatest(0.0, (coalesce(length(text), 0) - {n} + 1) / {n}.0)), 0)::DOUBLE, 4) AS eo_pct FROM {table} t JOIN {best_} b USING ({key}) GROUP BY ROLLUP({group})"


def page_text(c: str) -> str:
    out = c
    for pattern in (r"(?s)<!--.*?-->", r"(?is)<script.*?</script>", r"(?is)<style.*?</style>", r"(?s)<[^>]*>"):
        out = f"regexp_replace({out}, '{pattern}', ' ', 'g')"
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        out = f"replace({out}, '{entity}', '{char}')"
    return out
