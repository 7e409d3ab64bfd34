"""URL filter: host/path rules first, then a weighted vocabulary matched by an Aho-Corasick automaton.

Strict terms reject alone; soft terms reject when `soft_limit` distinct ones
occur.  A hit counts only between boundaries: the characters beside it, if any,
are not ASCII letters or digits.
"""

from __future__ import annotations

from collections.abc import Iterable

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

STRICT = ("porn", "xxx", "hentai", "spam-farm", "casino", "malware", "phishing", "warez")
SOFT = ("adult", "sex", "nude", "cam", "bet", "poker", "slots", "pills", "cheap", "free", "win", "loan", "crack", "torrent", "utm_source=feed")
#: (action, host, path)
RULES = (("allow", "com", "/"), ("block", "example.com", "/en/"), ("allow", "www.example.com", "/en/"), ("block", "net", "/es/"), ("block", "net", "/fr/"))


def host_of(url: Column) -> Column:
    """After the first :// up to /, ?, # or the end, A-Z lower-cased; empty without ://."""
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise("")
    return F.coalesce(F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), F.lit(""))


def path_of(url: Column) -> Column:
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url))).otherwise("")
    return F.coalesce(F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1), F.lit(""))


def ruled(host: Column, path: Column, rules: Iterable[tuple[str, str, str]] = RULES) -> Column:
    """Struct (rule, action) of the longest rule that fits host and path, null if none does."""
    ordered = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r))
    out = F.lit(None).cast("struct<rule:string,action:string>")
    for action, h, p in reversed(ordered):
        fits = ((host == h) | host.endswith(f".{h}")) & path.startswith(p)
        out = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(action).alias("action"))).otherwise(out)
    return out


def _bound(text: str, at: int) -> bool:
    return not (0 <= at < len(text) and text[at].isascii() and text[at].isalnum())


def vocabulary_hits(urls: Iterable[str | None], strict: Iterable[str], soft: Iterable[str]) -> list[tuple[int, int]]:
    """(strict hits, distinct soft terms hit) of each url; A-Z lower-cased, null as empty."""
    import ahocorasick

    automaton = ahocorasick.Automaton()
    for kind, terms in ((0, soft), (1, strict)):
        for term in terms:
            automaton.add_word(term.lower(), (kind, term.lower()))
    automaton.make_automaton()
    out = []
    for url in urls:
        text = "".join(c.lower() if c.isascii() else c for c in url or "")
        n_strict, kinds = 0, set()
        for end, (kind, term) in automaton.iter(text):
            if _bound(text, end + 1) and _bound(text, end - len(term)):
                if kind:
                    n_strict += 1
                else:
                    kinds.add(term)
        out.append((n_strict, len(kinds)))
    return out


def judge(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", strict=STRICT, soft=SOFT, soft_limit: int = 2, rules=RULES) -> DataFrame:
    """One row per page: page_id, host, path, rule, verdict, strict_hits, soft_hits.

    Where no rule fits, the vocabulary decides.  A null url or one without ://
    has empty host and path (the vocabulary still sees the whole url); null ids
    and repeated rows pass through; an empty table gives no rows.
    """
    if not strict and not soft:
        raise ValueError("an empty vocabulary")
    strict, soft = tuple(strict), tuple(soft)

    def run(batches):
        for batch in batches:
            hits = vocabulary_hits(batch.column(1).to_pylist(), strict, soft)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([h[0] for h in hits], pa.int32()), pa.array([h[1] for h in hits], pa.int32())], names=["page_id", "url", "strict_hits", "soft_hits"])

    narrow = pages.select(F.col(id_col).cast("bigint").alias("page_id"), F.col(url_col).cast("string").alias("url"))
    counted = narrow.mapInArrow(run, "page_id bigint, url string, strict_hits int, soft_hits int")
    named = counted.withColumns({"host": host_of(F.col("url")), "path": path_of(F.col("url"))}).withColumn("r", ruled(F.col("host"), F.col("path"), rules))
    own = F.when((F.col("strict_hits") >= 1) | (F.col("soft_hits") >= soft_limit), "block").otherwise("allow")
    return named.select("page_id", "host", "path", F.col("r.rule").alias("rule"), F.coalesce(F.col("r.action"), own).alias("verdict"), "strict_hits", "soft_hits")


def sql(strict=STRICT, soft=SOFT, soft_limit: int = 2, rules=RULES) -> str:
    import re

    def hit(term: str) -> str:
        safe = re.sub(r"([^a-z0-9])", r"\\\1", term)
        return f"CAST(regexp_matches(low, '(^|[^a-z0-9]){safe}([^a-z0-9]|$)') AS INTEGER)"

    ordered = sorted(rules, key=lambda r: (-len(r[1] + r[2]), r))
    case = lambda what: "CASE " + " ".join(f"WHEN (host = '{h}' OR host LIKE '%.{h}') AND starts_with(path, '{p}') THEN '{h + p if what == 'rule' else a}'" for a, h, p in ordered) + " END"
    return f"""
WITH u AS (SELECT page_id, translate(coalesce(url, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS low,
                  CASE WHEN contains(url, '://') THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
s AS (SELECT page_id, low, translate(regexp_extract(rest, '^([^/?#]*)', 1, 's'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
             regexp_extract(rest, '^[^/?#]*([^?#]*)', 1, 's') AS path FROM u),
h AS (SELECT page_id, host, path, {case('rule')} AS rule, {case('action')} AS action,
             {' + '.join(map(hit, strict))} AS n_strict, {' + '.join(map(hit, soft))} AS n_soft FROM s)
SELECT page_id, host, path, rule, coalesce(action, CASE WHEN n_strict >= 1 OR n_soft >= {soft_limit} THEN 'block' ELSE 'allow' END) AS verdict,
       n_soft AS soft_hits FROM h
"""
