"""URL filters: pattern rules found through their rarest literal token.

A rule is a host with a path prefix, or a free regular expression with the literal tokens that any match
must contain. Every rule is filed under the token that the fewest URLs of the table hold; the tokens of a
URL fetch candidate rules, and only those run their regular expression. A rule whose matches hold one of several
tokens is given as one rule for each; rules without any whole literal token are candidates of every URL. Of fitting host rules the longest decides; without one, a fitting free rule
decides; else the default.

The token counts gathered from the table have at most one row per rule token, so their size is bounded by
the rule list. Defined cases: a null URL or one without `://` has empty host and path and gets the default;
repeated rows are judged each; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from collections import defaultdict
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TOKEN = re.compile(r"[a-z0-9]+")
SPLIT = r"[^a-z0-9]+"


@dataclass(frozen=True)
class Rule:
    """name as reported; verdict allow or block; pattern over `host` + `path` (host rules) or the whole URL; tokens every match contains."""

    name: str
    verdict: str
    pattern: str
    tokens: tuple[str, ...]
    by_host: bool


def host_rule(verdict: str, spec: str) -> Rule:
    """`example.org/es/`: host example.org and its subdomains, path starting with /es/."""
    host, slash, path = spec.partition("/")
    path = slash + path
    whole = TOKEN.findall(path)
    if whole and not path.endswith("/") and TOKEN.match(path[-1]):
        whole.pop()  # the last token may go on in the URL
    pattern = rf"(?:[^\x00]*\.)?{re.escape(host)}\x00{re.escape(path)}"
    return Rule(spec, verdict, pattern, tuple(dict.fromkeys([*TOKEN.findall(host.lower()), *(t.lower() for t in whole)])), True)


def free_rule(name: str, verdict: str, pattern: str, tokens: tuple[str, ...]) -> Rule:
    return Rule(name, verdict, pattern, tokens, False)


#: The rules of the production query.
RULES = (
    host_rule("allow", "org/"),
    host_rule("block", "example.org/es/"),
    host_rule("block", "example.org/en/1"),
    host_rule("allow", "com/fr/"),
    host_rule("block", "com/de/"),
    free_rule("tracking", "block", r"[?&]utm_source=", ("utm", "source")),
    *(free_rule("executable", "block", rf"\.{kind}(?:$|[?#])", (kind,)) for kind in ("exe", "zip", "dmg")),
)


def split_url(url: str | None) -> tuple[str, str]:
    """Host with A-Z lowered, and path; both empty without `://`."""
    if url is None or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    end = re.search(r"[/?#]", rest)
    host = rest if end is None else rest[: end.start()]
    tail = "" if end is None or end.group() != "/" else re.split(r"[?#]", rest[end.start() :], maxsplit=1)[0]
    return host.translate(LOWER), tail


LOWER = {c: c + 32 for c in range(65, 91)}


class RuleIndex:
    def __init__(self, rules: tuple[Rule, ...], counts: dict[str, int]):
        self.filed: dict[str, list[tuple[Rule, re.Pattern]]] = defaultdict(list)
        self.always: list[tuple[Rule, re.Pattern]] = []
        for rule in rules:
            entry = (rule, re.compile(rule.pattern))
            if rule.tokens:
                self.filed[min(rule.tokens, key=lambda t: (counts.get(t, 0), -len(t), t))].append(entry)
            else:
                self.always.append(entry)

    def candidates(self, url: str) -> list[tuple[Rule, re.Pattern]]:
        found = list(self.always)
        for token in set(TOKEN.findall(url.translate(LOWER))):
            found += self.filed.get(token, ())
        return found

    def judge(self, url: str | None, default: str) -> tuple[str, str, str | None, str]:
        host, path = split_url(url)
        best: Rule | None = None
        free: Rule | None = None
        for rule, pattern in self.candidates(url or ""):
            if rule.by_host:
                if host and pattern.match(f"{host}\x00{path}") and (best is None or len(rule.name) > len(best.name)):
                    best = rule
            elif pattern.search(url or "") and (free is None or rule.name < free.name):
                free = rule
        return host, path, best and best.name, best.verdict if best else free.verdict if free else default


def token_counts(pages: DataFrame, url_col: str, rules: tuple[Rule, ...]) -> dict[str, int]:
    """URLs of the whole table that hold each rule token; at most one row per rule token reaches the driver."""
    wanted = sorted({t for r in rules for t in r.tokens})
    tokens = F.array_intersect(F.array_distinct(F.split(F.lower(F.col(f"`{url_col}`")), SPLIT)), F.array(*map(F.lit, wanted)))
    rows = pages.select(F.explode(tokens).alias("token")).groupBy("token").count().collect() if wanted else []
    return {r["token"]: r["count"] for r in rows}


def filter_urls(pages: DataFrame, rules: tuple[Rule, ...] = RULES, default: str = "allow", id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """Host, path, deciding host rule and verdict of every page."""
    index = RuleIndex(rules, token_counts(pages, url_col, rules))

    def judged(batches):
        for batch in batches:
            urls = batch.column(1).to_pylist()
            host, path, rule, verdict = zip(*(index.judge(u, default) for u in urls), strict=True) if urls else ((), (), (), ())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(x, pa.string()) for x in (host, path, rule, verdict))], ["page_id", "host", "path", "rule", "verdict"]
            )

    return pages.select(F.col(f"`{id_col}`").cast("long").alias("page_id"), F.col(f"`{url_col}`").cast("string").alias("url")).mapInArrow(
        judged, "page_id long, host string, path string, rule string, verdict string"
    )
