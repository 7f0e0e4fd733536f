"""Phonetic codes of lower-case words a-z as chains of built-in functions; the two metaphones in Python.

Chains are lists of (pattern, replacement) without look-behind or back-references where SQL twins
need them; repeats collapse letter by letter.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from functools import lru_cache, reduce

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F

LETTERS = "abcdefghijklmnopqrstuvwxyz"


def chain(word: Column, steps: list[tuple[str, str]]) -> Column:
    """Apply the replacements in order, each everywhere."""
    return reduce(lambda x, s: F.regexp_replace(x, s[0], s[1]), steps, word)


def collapse(letters: str) -> list[tuple[str, str]]:
    """Steps that leave one of each run of equal letters."""
    return [(f"{c}{c}+", c) for c in letters]


#: Codes of A to Z.
REFINED_CODES = "01360240043788015936020505"


def refined_soundex(word: Column) -> Column:
    codes = F.translate(word, LETTERS, REFINED_CODES)
    return F.concat(F.upper(F.substring(word, 1, 1)), chain(codes, collapse("0123456789")))


def sql_refined_soundex(x: str) -> str:
    """The same as DuckDB SQL."""
    out = f"translate({x}, '{LETTERS}', '{REFINED_CODES}')"
    for c in "0123456789":
        out = f"regexp_replace({out}, '{c}{c}+', '{c}', 'g')"
    return f"upper({x}[1]) || {out}"


def sql_chain(x: str, steps: list[tuple[str, str]]) -> str:
    """A chain as DuckDB SQL; group references are written as DuckDB wants them."""
    for pattern, new in steps:
        new = new.replace("$", "\\")
        x = f"regexp_replace({x}, '{pattern}', '{new}', 'g')"
    return x


#: The published rule table of Caverphone 1.
CAVERPHONE_START = [
    ("^cough", "cou2f"), ("^rough", "rou2f"), ("^tough", "tou2f"), ("^enough", "enou2f"), ("^gn", "2n"), ("mb$", "m2"),
    ("cq", "2q"), ("ci", "si"), ("ce", "se"), ("cy", "sy"), ("tch", "2ch"), ("c", "k"), ("q", "k"), ("x", "k"), ("v", "f"),
    ("dg", "2g"), ("tio", "sio"), ("tia", "sia"), ("d", "t"), ("ph", "fh"), ("b", "p"), ("sh", "s2"), ("z", "s"),
]
CAVERPHONE1 = [
    *CAVERPHONE_START,
    ("^[aeiou]", "A"), ("[aeiou]", "3"), ("3gh3", "3kh3"), ("gh", "22"), ("g", "k"),
    ("s+", "S"), ("t+", "T"), ("p+", "P"), ("k+", "K"), ("f+", "F"), ("m+", "M"), ("n+", "N"),
    ("w3", "W3"), ("wy", "Wy"), ("wh3", "Wh3"), ("why", "Why"), ("w", "2"), ("^h", "A"), ("h", "2"),
    ("r3", "R3"), ("ry", "Ry"), ("r", "2"), ("l3", "L3"), ("ly", "Ly"), ("l", "2"),
    ("j", "y"), ("y3", "Y3"), ("y", "2"), ("2", ""), ("3", ""),
]


def caverphone1(word: Column) -> Column:
    code = F.substring(F.concat(chain(word, CAVERPHONE1), F.lit("111111")), 1, 6)
    return F.when(F.length(word) < 2, F.lit("111111")).otherwise(code)


def sql_caverphone1(x: str) -> str:
    return f"CASE WHEN length({x}) < 2 THEN '111111' ELSE left({sql_chain(x, CAVERPHONE1)} || '111111', 6) END"


#: The published rule table of Caverphone 2.
CAVERPHONE2 = [
    ("e$", ""),
    ("^cough", "cou2f"), ("^rough", "rou2f"), ("^tough", "tou2f"), ("^enough", "enou2f"), ("^trough", "trou2f"), ("^gn", "2n"), ("mb$", "m2"),
    ("cq", "2q"), ("ci", "si"), ("ce", "se"), ("cy", "sy"), ("tch", "2ch"), ("c", "k"), ("q", "k"), ("x", "k"), ("v", "f"),
    ("dg", "2g"), ("tio", "sio"), ("tia", "sia"), ("d", "t"), ("ph", "fh"), ("b", "p"), ("sh", "s2"), ("z", "s"),
    ("^[aeiou]", "A"), ("[aeiou]", "3"), ("j", "y"), ("^y3", "Y3"), ("^y", "A"), ("y", "3"), ("3gh3", "3kh3"), ("gh", "22"), ("g", "k"),
    ("s+", "S"), ("t+", "T"), ("p+", "P"), ("k+", "K"), ("f+", "F"), ("m+", "M"), ("n+", "N"),
    ("w3", "W3"), ("wh3", "Wh3"), ("w$", "3"), ("w", "2"), ("^h", "A"), ("h", "2"), ("r3", "R3"), ("r$", "3"), ("r", "2"),
    ("l3", "L3"), ("l$", "3"), ("l", "2"), ("2", ""), ("3$", "A"), ("3", ""),
]


def caverphone2(word: Column) -> Column:
    return F.substring(F.concat(chain(word, CAVERPHONE2), F.lit("1111111111")), 1, 10)


def sql_caverphone2(x: str) -> str:
    return f"left({sql_chain(x, CAVERPHONE2)} || '1111111111', 10)"


#: Match rating: doubled consonants become one, vowels behind the first letter go.
_RATING = [*[(f"{c}{c}", c) for c in "bcdfghjklmnpqrstvwxyz"]]


def match_rating(word: Column) -> Column:
    rest = F.regexp_replace(F.substring(word, 2, 1 << 30), "[aeiou]", "")
    out = chain(F.concat(F.substring(word, 1, 1), rest), _RATING)
    out = F.when(F.length(out) > 6, F.concat(F.substring(out, 1, 3), F.right(out, F.lit(3)))).otherwise(out)
    return F.when(F.length(word) < 2, F.lit("")).otherwise(F.upper(out))


def sql_match_rating(x: str) -> str:
    out = sql_chain(f"({x}[1] || regexp_replace({x}[2:], '[aeiou]', '', 'g'))", _RATING)
    out = f"CASE WHEN length({out}) > 6 THEN left({out}, 3) || right({out}, 3) ELSE {out} END"
    return f"CASE WHEN length({x}) < 2 THEN '' ELSE upper({out}) END"


#: NYSIIS: beginnings, ends, then inner letters by rule; fixed values of the published table.
_NYSIIS_EDGE = [
    ("^mac", "mcc"), ("^kn", "nn"), ("^k", "c"), ("^(?:ph|pf)", "ff"), ("^sch", "sss"),
    ("(?:ee|ie)$", "y"), ("(?:dt|rt|rd|nt|nd)$", "d"),
    ("^([bcdfgjklmnpqrstvwxyz])h", "$1$1"),
]
_NYSIIS_INNER = [
    ("ev", "af"), ("[eiou]", "a"), ("q", "g"), ("z", "s"), ("m", "n"), ("kn", "n"), ("k", "c"), ("sch", "sss"), ("ph", "ff"),
    ("([bcdfgjklmnpqrstvwxyz])h", "$1$1"), ("h([bcdfghjklmnpqrstvwxyz])", "$1"), ("aw", "a"), ("h$", ""),
]
_NYSIIS_END = [*collapse(LETTERS), ("s$", ""), ("ay$", "y"), ("a$", "")]


def nysiis(word: Column) -> Column:
    """A chain after the published rules, full length; words that the rules empty give no code."""
    edged = chain(word, _NYSIIS_EDGE)
    first, rest = F.substring(edged, 1, 1), F.substring(edged, 2, 1 << 30)
    inner = chain(rest, _NYSIIS_INNER)
    whole = chain(F.concat(first, F.lit("|"), inner), [(f"^{c}\\|{c}*", f"{c}") for c in LETTERS])
    out = chain(F.substring(whole, 2, 1 << 30), _NYSIIS_END)
    return F.upper(F.concat(first, out))


def sql_nysiis(x: str) -> str:
    edged = sql_chain(x, _NYSIIS_EDGE)
    whole = sql_chain(f"(left({edged}, 1) || '|' || {sql_chain(f'substr({edged}, 2)', _NYSIIS_INNER)})", [(f"^{c}\\|{c}*", c) for c in LETTERS])
    return f"upper(left({edged}, 1) || {sql_chain(f'substr({whole}, 2)', _NYSIIS_END)})"


#: Cologne phonetics; fixed values of the published table. Capitals are codes that are set already.
_COLOGNE = [
    ("[dt]([csz])", "8$1"), ("^c([ahkloqrux])", "4$1"), ("^c", "8"), ("([sz])c", "$18"), ("c([ahkoqux])", "4$1"), ("c", "8"),
    ("ph", "33"), ("([ckq4])x", "$18"), ("x", "48"),
    ("[aeijouy]", "0"), ("[bp]", "1"), ("[dt]", "2"), ("[fvw]", "3"), ("[gkq]", "4"), ("l", "5"), ("[mn]", "6"), ("r", "7"), ("[sz]", "8"), ("h", ""),
    *collapse("0123456789"), ("^0", "A"), ("0", ""), ("A", "0"),
]


def cologne(word: Column) -> Column:
    return chain(word, _COLOGNE)


def sql_cologne(x: str) -> str:
    return sql_chain(x, _COLOGNE)


def metaphone(word: str, most: int = 4) -> str:
    """Metaphone of a word a-z, up to ``most`` codes."""
    w = word.upper()
    if len(w) < 2:
        return w
    if w[:2] in ("KN", "GN", "PN", "AE", "WR"):
        w = w[1:]
    elif w[0] == "X":
        w = "S" + w[1:]
    elif w[:2] == "WH":
        w = "W" + w[2:]
    out: list[str] = []
    front, i = "EIY", 0
    at = lambda k: w[k] if 0 <= k < len(w) else ""
    while i < len(w) and len(out) < most:
        c, nxt, prev = w[i], at(i + 1), at(i - 1)
        if c == prev and c != "C":
            i += 1
            continue
        if c in "AEIOU":
            if i == 0:
                out.append(c)
        elif c == "B":
            if not (prev == "M" and i == len(w) - 1):
                out.append("B")
        elif c == "C":
            if prev == "S" and nxt and nxt in front:
                pass
            elif w[i : i + 3] == "CIA":
                out.append("X")
            elif nxt and nxt in front:
                out.append("S")
            elif prev == "S" and nxt == "H":
                out.append("K")
            elif nxt == "H":
                out.append("K" if i == 0 and len(w) >= 3 and at(2) in "AEIOU" else "X")
            else:
                out.append("K")
        elif c == "D":
            if nxt == "G" and at(i + 2) and at(i + 2) in front:
                out.append("J")
                i += 2
            else:
                out.append("T")
        elif c == "G":
            if nxt == "H" and (i + 1 == len(w) - 1 or (at(i + 2) and at(i + 2) not in "AEIOU")):
                pass
            elif i > 0 and (w[i:] == "GN" or w[i:] == "GNED"):
                pass
            else:
                out.append("J" if nxt and nxt in front and prev != "G" else "K")
        elif c == "H":
            if i < len(w) - 1 and not (i > 0 and prev in "CSPTG") and nxt in "AEIOU":
                out.append("H")
        elif c in "FJLMNR":
            out.append(c)
        elif c == "K":
            if prev != "C":
                out.append("K")
        elif c == "P":
            out.append("F" if nxt == "H" else "P")
        elif c == "Q":
            out.append("K")
        elif c == "S":
            out.append("X" if nxt == "H" or w[i : i + 3] in ("SIO", "SIA") else "S")
        elif c == "T":
            if w[i : i + 3] in ("TIA", "TIO"):
                out.append("X")
            elif w[i : i + 3] == "TCH":
                pass
            else:
                out.append("0" if nxt == "H" else "T")
        elif c == "V":
            out.append("F")
        elif c in "WY":
            if nxt and nxt in "AEIOU":
                out.append(c)
        elif c == "X":
            out += ["K", "S"]
        elif c == "Z":
            out.append("S")
        i += 1
    return "".join(out)[:most]


#: Double Metaphone; fixed values of the published rules, by letter, first match wins: pattern at the letter, code, other
#: code (None: the same), letters read, and a trait that the word must have or, after "-", must not have.
_DOUBLE = {
    "b": [("bb", "P", None, 2, ""), ("b", "P", None, 1, "")],
    "c": [
        ("chia", "K", None, 2, ""), ("(?<=[^aeiouy]a)ch(?![ie])", "K", None, 2, ""), ("(?<=[bm]a)cher", "K", None, 2, ""),
        ("^caesar", "S", None, 2, ""),
        ("(?<!^)chae", "K", "X", 2, ""), ("^ch(?:arac|aris|or(?!e)|ym|ia|em)", "K", None, 2, ""),
        ("ch", "K", None, 2, "sch"), ("(?<=or)ch(?:es|id)|(?<=ar)chit", "K", None, 2, ""), ("ch[ts]", "K", None, 2, ""),
        ("(?:(?<=[aoue])|^)ch(?:[lrnmbhfvw]|$)", "K", None, 2, ""),
        ("(?<!^)ch", "K", None, 2, "mc"), ("(?<!^)ch", "X", "K", 2, ""), ("ch", "X", None, 2, ""),
        ("(?<!wi)cz", "S", "X", 2, ""), ("ccia", "X", None, 3, ""),
        ("(?<=^a)cc(?:[ie]|h(?!u))|(?<=u)cce[es]", "KS", None, 3, ""), ("(?<!^m)cc(?:[ie]|h(?!u))", "X", None, 3, ""), ("(?<!^m)cc", "K", None, 2, ""),
        ("c[kgq]", "K", None, 2, ""), ("ci[oea]", "S", "X", 2, ""), ("c[iey]", "S", None, 2, ""), ("c(?:[kq]|c(?![ei]))", "K", None, 2, ""), ("c", "K", None, 1, ""),
    ],
    "d": [("dg[iey]", "J", None, 3, ""), ("dg", "TK", None, 2, ""), ("d[td]", "T", None, 2, ""), ("d", "T", None, 1, "")],
    "f": [("ff", "F", None, 2, ""), ("f", "F", None, 1, "")],
    "g": [
        ("(?<=[^aeiouy])gh", "K", None, 2, ""), ("^ghi", "J", None, 2, ""), ("^gh", "K", None, 2, ""),
        ("(?<=[bhd].)gh|(?<=[bhd]..)gh|(?<=[bh]...)gh", "", None, 2, ""), ("(?<=[cglrt].u)gh", "F", None, 2, ""), ("(?<!i)gh", "K", None, 2, ""), ("gh", "", None, 2, ""),
        ("(?<=^[aeiouy])gn", "KN", "N", 2, "-slavic"), ("gn(?!ey)", "N", "KN", 2, "-slavic"), ("gn", "KN", None, 2, ""),
        ("gli", "KL", "L", 2, "-slavic"), ("^g(?:y|e[spblyir]|i[blne])", "K", "J", 2, ""),
        ("(?<![ei])g(?:er|y)(?<!rgy)(?<!ogy)", "K", "J", 2, "-anger"),
        ("g[eiy]|(?<=[ao])ggi", "K", None, 2, "sch"), ("get", "K", None, 2, ""), ("gier", "J", None, 2, ""), ("g[eiy]|(?<=[ao])ggi", "J", "K", 2, ""),
        ("gg", "K", None, 2, ""), ("g", "K", None, 1, ""),
    ],
    "h": [("(?:^|(?<=[aeiouy]))h[aeiouy]", "H", None, 2, ""), ("h", "", None, 1, "")],
    "j": [
        ("^jose$", "H", None, 1, ""), ("jose", "J", "H", 1, ""), ("^jj", "J", "A", 2, ""), ("^j", "J", "A", 1, ""),
        ("(?<=[aeiouy])j[ao]", "J", "H", 1, "-slavic"), ("j$", "J", " ", 1, ""), 
        ("(?<![skl])jj", "J", None, 2, ""), ("(?<![skl])j(?![ltksnmbz])", "J", None, 1, ""), ("jj", "", None, 2, ""), ("j", "", None, 1, ""),
    ],
    "k": [("kk", "K", None, 2, ""), ("k", "K", None, 1, "")],
    "l": [
        ("(?<=i)ll[oa]$|(?<=a)lle$", "L", "", 2, ""), ("(?<=a)lle", "L", "", 2, "spanish"), ("ll", "L", None, 2, ""), ("l", "L", None, 1, ""),
    ],
    "m": [("mm|(?<=u)mb(?:$|er)", "M", None, 2, ""), ("m", "M", None, 1, "")],
    "n": [("nn", "N", None, 2, ""), ("n", "N", None, 1, "")],
    "p": [("ph", "F", None, 2, ""), ("p[pb]", "P", None, 2, ""), ("p", "P", None, 1, "")],
    "q": [("qq", "K", None, 2, ""), ("q", "K", None, 1, "")],
    "r": [("(?<=ie)(?<!m[ea]ie)r$", "", "R", 1, "-slavic"), ("rr", "R", None, 2, ""), ("r", "R", None, 1, "")],
    "s": [
        ("(?<=[iy])sl", "", None, 1, ""), ("^sugar", "X", "S", 1, ""), ("sh(?:eim|oek|olm|olz)", "S", None, 2, ""), ("sh", "X", None, 2, ""),
        ("si[oa]", "S", None, 3, "slavic"), ("si[oa]", "S", "X", 3, ""), ("sz", "S", "X", 2, ""), ("^s[mnlw]", "S", "X", 1, ""),
        ("sche[rn]", "X", "SK", 3, ""), ("sch(?:oo|uy|e[dm])", "SK", None, 3, ""), ("^sch(?![aeiouyw])", "X", "S", 3, ""), ("sch", "X", None, 3, ""),
        ("sc[iey]", "S", None, 3, ""), ("sc", "SK", None, 3, ""), ("(?<=[ao]i)s$", "", "S", 1, ""), ("ss", "S", None, 2, ""), ("s", "S", None, 1, ""),
    ],
    "t": [
        ("tion|tia|tch", "X", None, 3, ""), ("th[oa]m", "T", None, 2, ""), ("tth", "T", None, 2, "sch"), ("th", "T", None, 2, "sch"),
        ("tth|th", "0", "T", 2, ""), ("t[td]", "T", None, 2, ""), ("t", "T", None, 1, ""),
    ],
    "v": [("vv", "F", None, 2, ""), ("v", "F", None, 1, "")],
    "w": [
        ("wr", "R", None, 2, ""), ("^w[aeiouy]", "A", "F", 1, ""), ("^wh", "A", None, 1, ""), ("(?<=[aeiouy])w$|(?<=[eo])wsk[iy]", "", "F", 1, ""),
        ("w", "", "F", 1, "sch"), ("wi[ct]z", "TS", "FX", 4, ""), ("w", "", None, 1, ""),
    ],
    "x": [("^x", "S", None, 1, ""), ("(?<=iau)x$|(?<=eau)x$|(?<=[ao]u)x$", "", None, 1, ""), ("x[cx]", "KS", None, 2, ""), ("x", "KS", None, 1, "")],
    "z": [
        ("zh", "J", None, 2, ""), ("zz[oia]", "S", "TS", 2, ""), ("(?<=[^t])zz", "S", "TS", 2, "slavic"), ("(?<=[^t])z", "S", "TS", 1, "slavic"),
        ("zz", "S", None, 2, ""), ("z", "S", None, 1, ""),
    ],
}
for _c in "aeiouy":
    _DOUBLE[_c] = [(f"^{_c}", "A", None, 1, ""), (_c, "", None, 1, "")]
_RULES = {c: [(re.compile(p), a, a if b is None else b, n, t) for p, a, b, n, t in rules] for c, rules in _DOUBLE.items()}
_TRAITS = {
    "slavic": re.compile("[wk]|cz"),
    "sch": re.compile("^sch"),
    "mc": re.compile("^mc"),
    "anger": re.compile("^[drm]anger"),
    "spanish": re.compile("(?:as|os|a|o)$"),
}
_SILENT = re.compile("^(?:[gkp]n|wr|ps)")


def double_metaphone(word: str, most: int = 4) -> tuple[str, str]:
    """Both codes of a word a-z, up to ``most`` letters each; they are equal where the rules know one sound."""
    traits = {name for name, p in _TRAITS.items() if p.search(word)}
    codes, at = ["", ""], 1 if _SILENT.match(word) else 0
    while at < len(word) and min(map(len, codes)) < most:
        for pattern, one, two, step, trait in _RULES[word[at]]:
            if pattern.match(word, at) and (not trait or (trait[1:] not in traits if trait[0] == "-" else trait in traits)):
                codes = [(codes[0] + one)[:most], (codes[1] + two)[:most]]
                at += step
                break
    return codes[0], codes[1]


def _token_keys(values: Column, code: Callable[[str], tuple[str, ...]]) -> Column:
    """Codes of the tokens of a value; Arrow batches, a worker codes a token once while it is among its latest."""

    def keys(text: str | None) -> list[str]:
        words = _OTHERS.sub(" ", (text or "").lower()).split()
        return sorted({c for t in words if t.isalpha() for c in code(t)} - {""})

    @F.pandas_udf("array<string>")
    def coded(texts: pd.Series) -> pd.Series:
        return texts.map(keys)

    return coded(values)


_OTHERS = re.compile("[^a-z0-9]+")


@lru_cache(maxsize=1 << 16)
def _single(token: str) -> tuple[str, ...]:
    return (metaphone(token),)


@lru_cache(maxsize=1 << 16)
def _double(token: str) -> tuple[str, str]:
    return double_metaphone(token)


def metaphone_keys(values: Column) -> Column:
    """Metaphones of the tokens of a value."""
    return _token_keys(values, lambda t: _single(t))


def double_metaphone_keys(values: Column) -> Column:
    """Both codes of the tokens of a value, each key once."""
    return _token_keys(values, lambda t: _double(t))
