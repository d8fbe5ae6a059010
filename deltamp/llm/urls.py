"""URL filters: host and path rules first, then pattern rules found through their rarest literal token.

A pattern's alternatives are spread out into variants, and each variant's regular expression is read for
the literal tokens that every match holds whole: runs of [a-z0-9] with something else proved on either
side. A counting pass over the URLs (only such tokens, so at most a few per rule) tells which of a
variant's tokens is rarest, and the rule is filed under it. A URL's tokens then fetch candidate rules, and
only those run their regular expression. A rule with a variant that proves no token is refused, so the
verdict never depends on what else is in the table.

Defined results: a null URL, or one without ://, has empty host and path, no rule, and the method's
verdict over the text there is; repeated rows repeat their verdicts; an empty table gives no rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from re import _constants as C
from re import _parser as regex_parser

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import as_texts

_TOKEN = re.compile(r"[a-z0-9]+")
_HOST = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


MOST_VARIANTS = 64
_ALNUM = frozenset(map(ord, "abcdefghijklmnopqrstuvwxyz0123456789"))
# What a step of a variant may be: one known character, one of unknown ones that are or aren't token
# characters (or may be either), or an edge of the URL.
_SEPARATOR, _INSIDE, _UNKNOWN = "separator", "inside", "unknown"


def _charset(items: list) -> str:
    """Whether the characters of a class are all separators, all token characters, or either."""
    if items and items[0][0] is C.NEGATE:
        return _UNKNOWN
    points: set[int] = set()
    for op, arg in items:
        if op is C.LITERAL:
            points.add(arg)
        elif op is C.RANGE:
            points.update(range(arg[0], arg[1] + 1))
        else:
            return _UNKNOWN
    return _SEPARATOR if not points & _ALNUM else _INSIDE if points <= _ALNUM else _UNKNOWN


def _variants(parsed) -> list[list]:
    """The step lists of a parsed expression, one for each way through its alternatives."""
    out: list[list] = [[]]
    for op, arg in parsed:
        if op is C.LITERAL:
            steps = [[chr(arg)]]
        elif op is C.IN:
            steps = [[_charset(arg)]]
        elif op is C.AT and arg in (C.AT_BEGINNING, C.AT_BEGINNING_STRING, C.AT_END, C.AT_END_STRING):
            steps = [[_SEPARATOR]]
        elif op is C.SUBPATTERN:
            steps = _variants(arg[3])
        elif op is C.BRANCH:
            steps = [v for branch in arg[1] for v in _variants(branch)]
        elif op in (C.MAX_REPEAT, C.MIN_REPEAT):
            low, high, inner = arg
            some = _variants(inner)
            # Of a repetition only its first and last pass are known; what lies between is anything.
            repeated = [[*a, _UNKNOWN, *b] for a in some for b in some] if high > 1 else []
            steps = ([[]] if low == 0 else []) + some + repeated
        else:
            steps = [[_UNKNOWN]]
        out = [a + b for a in out for b in steps]
        if len(out) > MOST_VARIANTS:
            raise ValueError("a pattern has over MOST_VARIANTS alternatives: write it as several")
    return out


def _kind(step: str) -> str:
    return step if len(step) > 1 else _INSIDE if ord(step) in _ALNUM else _SEPARATOR


def _whole_tokens(steps: list) -> frozenset[str]:
    """The literal tokens that stand whole in every string these steps match."""
    found, at = set(), 0
    while at < len(steps):
        end = at
        while end < len(steps) and len(steps[end]) == 1 and ord(steps[end]) in _ALNUM:
            end += 1
        if end > at and at > 0 and end < len(steps) and _kind(steps[at - 1]) == _kind(steps[end]) == _SEPARATOR:
            found.add("".join(steps[at:end]))
        at = max(end, at + 1)
    return frozenset(found)


def proved_tokens(regex: str) -> list[frozenset[str]]:
    """Token sets, one a variant: every match of the expression holds all tokens of one of them whole."""
    sets = set(map(_whole_tokens, _variants(regex_parser.parse(regex))))
    if frozenset() in sets:
        raise ValueError(f"{regex}: no literal token is proved; bound one on both sides")
    return sorted(sets, key=sorted)


# The contract's host and path rules, and this package's own pattern rules.
RULES = (("allow", "com", "/"), ("block", "example.com", "/en/"), ("allow", "www.example.com", "/en/"), ("block", "net", "/es/"), ("block", "net", "/fr/"))
PATTERNS = (
    r"://([a-z0-9-]+[.])*(spam-farm|casino-win|free-bets|cheap-pills|adult-x|ads-track)[.]",
    r"[?&]utm_source=spam(&|#|$)",
    r"/(casino|poker)(/|$)",
    r"://ads?[.]",
    r"/de/[0-9]+[.]html",
    r"[?&]page=2&ref=x",
    r"/tag/[a-z0-9-]+/feed(/|$)",
)


def parts(url: str) -> tuple[str, str]:
    """Host (A-Z lower-cased) and path."""
    at = url.find("://")
    if at < 0:
        return "", ""
    m = re.match(r"([^/?#]*)([^?#]*)", url[at + 3 :], re.S)
    return m[1].translate(_HOST), m[2]


def base_rule(host: str, path: str, rules=RULES) -> tuple[str, str] | None:
    """(action, rule) of the longest rule that fits."""
    fits = [(len(h + p), a, h + p) for a, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return max(fits)[1:] if fits else None


class PatternIndex:
    """Rules by the rarest proved token of each of their variants."""

    def __init__(self, patterns: tuple[str, ...], counts: dict[str, int]):
        self.by_token: dict[str, list] = {}
        for p in patterns:
            compiled = re.compile(p)
            for tokens in proved_tokens(p):
                rarest = min(tokens, key=lambda t: (counts.get(t, 0), -len(t), t))
                if compiled not in self.by_token.setdefault(rarest, []):
                    self.by_token[rarest].append(compiled)

    def blocks(self, url: str) -> bool:
        low = url.translate(_HOST)
        return any(r.search(low) for t in self.by_token.keys() & set(_TOKEN.findall(low)) for r in self.by_token[t])


def token_counts(urls: DataFrame, url_col: str, patterns: tuple[str, ...]) -> dict[str, int]:
    """In how many URLs each token that a rule names occurs: one row a token at most."""
    named = sorted({t for p in patterns for tokens in proved_tokens(p) for t in tokens})
    if not named:
        return {}
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    held = F.array_intersect(F.regexp_extract_all(F.translate(F.col(url_col).cast("string"), upper, upper.lower()), F.lit("[a-z0-9]+"), F.lit(0)), F.array(*map(F.lit, named)))
    return {r["t"]: r["n"] for r in urls.select(F.explode(held).alias("t")).groupBy("t").agg(F.count("*").alias("n")).collect()}


def filter_urls(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", rules=RULES, patterns: tuple[str, ...] = PATTERNS) -> DataFrame:
    """Per row: id, host, path, rule (null if none fits) and verdict."""
    shared = pages.sparkSession.sparkContext.broadcast(PatternIndex(patterns, token_counts(pages, url_col, patterns)))
    schema = T.StructType([T.StructField(id_col, pages.schema[id_col].dataType), *(T.StructField(c, T.StringType()) for c in ("host", "path", "rule", "verdict"))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = shared.value
        for b in batches:
            rows = []
            for url in as_texts(b.column(1)):
                host, path = parts(url)
                found = base_rule(host, path, rules)
                action = found[0] if found else "block" if index.blocks(url) else "allow"
                rows.append((host, path, found[1] if found else None, action))
            columns = [pa.array([r[k] for r in rows], pa.string()) for k in range(4)]
            yield pa.RecordBatch.from_arrays([b.column(0), *columns], names=schema.names)

    return pages.select(id_col, F.col(url_col).cast("string")).mapInArrow(run, schema)
