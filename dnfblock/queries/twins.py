"""DuckDB twins of indexing functions, atoms and schemes."""

from __future__ import annotations

from dnfblock.functions import phonetic
from dnfblock.operators.scheme import Atom, Scheme
from dnfblock.sources import datasets


def norm(x: str) -> str:
    return f"trim(regexp_replace(lower({x}), '[^a-z0-9]+', ' ', 'g'))"


def _all_tokens(x: str) -> str:
    return f"list_filter(string_split({norm(x)}, ' '), lambda t: t <> '')"


def _tokens(x: str) -> str:
    return f"list_distinct({_all_tokens(x)})"


def _ints(x: str) -> str:
    return f"list_distinct(list_transform(regexp_extract_all({x}, '[0-9]+'), lambda d: CASE WHEN ltrim(d, '0') = '' THEN '0' ELSE ltrim(d, '0') END))"


def _soundex(t: str) -> str:
    codes = "'abcdefghijklmnopqrstuvwxyz', '01230127022455012623017202'"
    x = f"(translate(left({t}, 1), {codes}) || translate(regexp_replace(substr({t}, 2), '[hw]', '', 'g'), {codes}))"
    for c in "01234567":
        x = f"regexp_replace({x}, '{c}{c}+', '{c}', 'g')"
    return f"(upper(left({t}, 1)) || left(regexp_replace(substr({x}, 2), '0', '', 'g') || '000', 3))"


_PHONETIC = {
    "soundex": _soundex, "refined_soundex": phonetic.sql_refined_soundex, "nysiis": phonetic.sql_nysiis, "caverphone1": phonetic.sql_caverphone1,
    "caverphone2": phonetic.sql_caverphone2, "match_rating": phonetic.sql_match_rating, "cologne": phonetic.sql_cologne,
}


def keys(name: str, x: str) -> str:
    """Keys of one string."""
    n = norm(x)
    if name == "exact":
        return f"list_filter([{n}], lambda t: t <> '')"
    if name == "first_digit":
        return f"CASE WHEN regexp_matches({x}, '^[0-9]') THEN [left({x}, 1)] ELSE []::VARCHAR[] END"
    if (name.startswith("first") and name != "first_sig_digits2") or name == "last3":
        size = int(name[-1])
        return f"CASE WHEN length({n}) >= {size} THEN [{'right' if name == 'last3' else 'left'}({n}, {size})] ELSE []::VARCHAR[] END"
    if name.startswith("qgram"):
        q = int(name[-1])
        return f"flatten(list_transform([{n}], lambda n: list_distinct(list_transform(range(1, length(n) - {q} + 2), lambda i: substr(n, i, {q})))))"
    if name.startswith("token_ng"):
        m, a = int(name[-1]), _all_tokens(x)
        return f"flatten(list_transform([{a}], lambda a: list_distinct(list_transform(range(1, len(a) - {m} + 2), lambda i: array_to_string(a[i:i + {m - 1}], ' ')))))"
    if name == "token":
        return _tokens(x)
    if name == "raw_token":
        return f"list_distinct(list_filter(regexp_split_to_array({x}, '\\s+'), lambda t: t <> ''))"
    if name == "token_prefix3":
        return f"list_distinct(list_transform({_tokens(x)}, lambda t: left(t, 3)))"
    if name == "token_sorted":
        return f"list_filter([array_to_string(list_sort({_all_tokens(x)}), '')], lambda t: t <> '')"
    if name == "common_int":
        return _ints(x)
    if name == "int_pm1":
        return f"list_distinct(flatten(list_transform({_ints(x)}, lambda d: [d, CAST(CAST(d AS BIGINT) + 1 AS VARCHAR)])))"
    if name == "first_sig_digits2":
        return f"list_distinct(list_transform({_ints(x)}, lambda d: left(d, 2)))"
    if name == "round10":
        return f"list_distinct(list_transform({_ints(x)}, lambda d: CAST(CAST(d AS BIGINT) // 10 AS VARCHAR)))"
    code = _PHONETIC[name]
    words = f"list_filter({_tokens(x)}, lambda t: regexp_full_match(t, '[a-z]+'))"
    return f"list_distinct(list_filter(list_transform({words}, lambda t: {code('t')}), lambda c: c <> ''))"


def atom_keys(atom: Atom, side: int) -> str:
    """Keys of a record: the union over the atom's set-valued fields."""
    parts = [f"flatten(list_transform(\"{f}\", lambda v: {keys(atom.gbp, 'v')}))" for f in atom.fields(side)]
    return f"list_distinct({' || '.join(parts)})"


def key_rows(scheme: Scheme, side: int, table: str) -> str:
    """SELECT of ``rid, term, key`` for all terms."""
    rows = []
    for i, term in enumerate(scheme.terms):
        cols = ", ".join(f"{atom_keys(a, side)} AS k{j}" for j, a in enumerate(term))
        value = "k0"
        for j in range(1, len(term)):
            value = f"flatten(list_transform({value}, lambda x{j}: list_transform(k{j}, lambda y{j}: x{j} || chr(31) || y{j})))"
        rows.append(f"SELECT rid, {i} AS term, unnest({value}) AS key FROM (SELECT rid, {cols} FROM {table})")
    return " UNION ALL ".join(rows)


def sides(pair: datasets.Pair) -> str:
    return f"l AS ({datasets.duck_side(pair.left)}), r AS ({datasets.duck_side(pair.right)}), truth AS ({datasets.duck(pair.truth_sql)})"


def candidate_ctes(pair: datasets.Pair, scheme: Scheme) -> str:
    """CTEs l, r, truth, lk, rk and c, the distinct candidate pairs."""
    return (
        f"WITH {sides(pair)}, lk AS ({key_rows(scheme, 0, 'l')}), rk AS ({key_rows(scheme, 1, 'r')}), "
        "c AS (SELECT DISTINCT lk.rid AS l_rid, rk.rid AS r_rid FROM lk JOIN rk ON lk.term = rk.term AND lk.key = rk.key)"
    )


def covers(scheme: Scheme, left: str, right: str) -> str:
    """The formula itself over key columns that :func:`cross_ctes` makes."""
    terms = []
    for i, term in enumerate(scheme.terms):
        terms.append("(" + " AND ".join(f"list_has_any({left}.k{i}_{j}, {right}.k{i}_{j})" for j in range(len(term))) + ")")
    return " OR ".join(terms)


def cross_ctes(pair: datasets.Pair, scheme: Scheme) -> str:
    """CTEs lx and rx with the keys of every atom, for a cross join."""
    cols = lambda s: ", ".join(f"{atom_keys(a, s)} AS k{i}_{j}" for i, t in enumerate(scheme.terms) for j, a in enumerate(t))
    return f"WITH {sides(pair)}, lx AS (SELECT rid, {cols(0)} FROM l), rx AS (SELECT rid, {cols(1)} FROM r)"


def cross(pair: datasets.Pair, scheme: Scheme) -> str:
    """All pairs, tested one by one."""
    return f"{cross_ctes(pair, scheme)} SELECT lx.rid AS l_rid, rx.rid AS r_rid FROM lx, rx WHERE {covers(scheme, 'lx', 'rx')}"


def class_links(pair: datasets.Pair, scheme: Scheme) -> str:
    """Every record's class of equal keys and its number of links, from all pairs, tested one by one."""
    parts = []
    for side, table in enumerate("lr"):
        parts.append(
            f"""SELECT {side} AS side, rid, min(rid) OVER (PARTITION BY keys) AS class_id, coalesce(links, 0) AS links
            FROM (SELECT t.rid, coalesce(list_sort(list(term || ':' || key) FILTER (WHERE key IS NOT NULL)), []) AS keys
            FROM {table} AS t LEFT JOIN ({key_rows(scheme, side, table)}) AS k ON k.rid = t.rid GROUP BY t.rid)
            LEFT JOIN (SELECT {table}_rid AS rid, count(*) AS links FROM c GROUP BY {table}_rid) USING (rid)"""
        )
    return f"WITH {sides(pair)}, c AS ({cross(pair, scheme)}) {' UNION ALL '.join(parts)}"
