"""URL filters by a sort-merge range join of reversed-host keys and rule intervals.

A host read label by label from the right ("com.example.www.") turns "this host and all its
subdomains" into one interval of sorted keys. Intervals of that kind nest or are disjoint, so one
sweep over the sorted keys keeps the rules that cover the current key on a stack: rules open and
close as the sweep passes, and a url is judged against the stack alone, longest rule first, with the
rule's path as the remaining prefix test.

Pages are swept where they lie: each task sorts the keys of its own batch, so a host with a third of
all rows needs no exchange. Rules go to the tasks in chunks of at most `RULES_AT_ONCE`, each sorted by
itself; more rules mean more passes, each of which keeps the longer of its rule and the one found before.

Defined results: a null url, or one without "://", has empty host and path, matches no rule and gets
the default verdict; ports and user names stay part of the host; repeated rows are judged each; of
two matching rules the longer text wins, then the longer host. Duplicate rules with opposite verdicts
resolve to block; rules without a text or a verdict are left out. Columns other than the named ones are not read.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import table

RULES_AT_ONCE = 100_000
RULES = (("block", "net/"), ("allow", "example.net/en/"), ("block", "example.com/de/"), ("allow", "org/fr/"))
_UP, _LOW = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_of(url: Column) -> Column:
    rest = F.substring_index(url, "://", 1)
    after = F.when(F.instr(url, "://") > 0, url.substr(F.length(rest) + 4, F.length(url)))
    return F.coalesce(F.translate(F.regexp_extract(after, r"^([^/?#]*)", 1), _UP, _LOW), F.lit(""))


def path_of(url: Column) -> Column:
    rest = F.substring_index(url, "://", 1)
    after = F.when(F.instr(url, "://") > 0, url.substr(F.length(rest) + 4, F.length(url)))
    return F.coalesce(F.regexp_extract(after, r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def canonical(host: str) -> str:
    """The host's labels from the right, each closed by a byte that sorts below every label byte."""
    return "".join(label + "\x00" for label in reversed(host.split(".")))


def ordered_rules(rules: Iterable[tuple[str, str]]) -> list[tuple[str, str, str, str]]:
    """(key, host, path, verdict) sorted by key, so that an enclosing interval comes before its parts."""
    seen: dict[tuple[str, str], str] = {}
    for verdict, rule in rules:
        if not verdict or not rule:
            continue
        host, slash, path = rule.partition("/")
        at = (host.lower(), slash + path)
        seen[at] = "block" if "block" in (verdict, seen.get(at)) else verdict
    return sorted((canonical(host), host, path, verdict) for (host, path), verdict in seen.items())


def sweep(hosts: list[str], paths: list[str], rules: list[tuple[str, str, str, str]]) -> list[tuple[str, str] | None]:
    """The winning (rule, verdict) of each url, or None: one pass over the sorted keys of the batch."""
    keys = [canonical(h) for h in hosts]
    out: list[tuple[str, str] | None] = [None] * len(keys)
    stack: list[tuple[str, str, str, str]] = []
    ranked: list[tuple[str, str, str, str]] = []
    coming = 0
    previous = None
    for i in sorted(range(len(keys)), key=keys.__getitem__):
        key = keys[i]
        if key != previous:
            while stack and not key.startswith(stack[-1][0]):
                stack.pop()
            if coming < len(rules) and rules[coming][0] <= key and not key.startswith(rules[coming][0]):
                # Rules between the last key and this one are skipped, up to the first label of this key.
                coming = bisect_left(rules, (key.partition("\x00")[0] + "\x00",), lo=coming)
            while coming < len(rules) and rules[coming][0] <= key:
                if key.startswith(rules[coming][0]):
                    stack.append(rules[coming])
                coming += 1
            ranked = sorted(stack, key=lambda r: (-len(r[1]) - len(r[2]), -len(r[1]), r[1]))
            previous = key
        if hosts[i]:
            out[i] = next(((r[1] + r[2], r[3]) for r in ranked if paths[i].startswith(r[2])), None)
    return out


def judge(pages: DataFrame, rules: Iterable[tuple[str, str]] | DataFrame = RULES, default: str = "allow", *, page_id: str = "page_id", url: str = "url") -> DataFrame:
    """page_id, host, path, rule and verdict of every page.

    rules: (verdict, rule text) pairs, or a DataFrame with columns verdict and rule, which is read in
    sorted chunks of RULES_AT_ONCE."""
    judged = pages.select(F.col(page_id), host_of(F.col(url)).alias("host"), path_of(F.col(url)).alias("path"), F.lit(None).cast("string").alias("rule"), F.lit(default).alias("verdict"))
    for chunk in _chunks(rules):
        judged = judged.mapInArrow(_pass(chunk), judged.schema)
    return judged


def _chunks(rules: Iterable[tuple[str, str]] | DataFrame) -> Iterator[list[tuple[str, str, str, str]]]:
    rows = ((r.verdict, r.rule) for r in rules.select("verdict", "rule").toLocalIterator()) if isinstance(rules, DataFrame) else iter(rules)
    while some := [r for r, _ in zip(rows, range(RULES_AT_ONCE), strict=False)]:
        yield ordered_rules(some)


def _pass(rules: list[tuple[str, str, str, str]]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            names = b.schema.names
            hosts, paths = b.column("host").to_pylist(), b.column("path").to_pylist()
            old, verdicts = b.column("rule").to_pylist(), b.column("verdict").to_pylist()
            for i, found in enumerate(sweep(hosts, paths, rules)):
                if found and _longer(found, old[i], verdicts[i]):
                    old[i], verdicts[i] = found
            yield pa.RecordBatch.from_arrays([b.column(names[0]), b.column("host"), b.column("path"), pa.array(old, pa.string()), pa.array(verdicts, pa.string())], names=names)

    return run


def _longer(found: tuple[str, str], old: str | None, verdict: str) -> bool:
    if old is None:
        return True
    rank = lambda rule: (len(rule), len(rule.partition("/")[0]))
    return rank(found[0]) > rank(old) or found[0] == old and verdict != "block"


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages"))


SQL = r"""
WITH split AS (
  SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages
), parts AS (
  SELECT page_id, translate(regexp_extract(coalesce(rest, ''), '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host,
         regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) AS path FROM split
), rules(verdict, rhost, rpath) AS (
  VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')
), hits AS (
  SELECT page_id, host, path, rhost || rpath AS rule, verdict, length(rhost || rpath) AS size FROM parts, rules
  WHERE ends_with('.' || host, '.' || rhost) AND starts_with(path, rpath)
), best AS (
  SELECT page_id, host, path, max_by(rule, size) AS rule, max_by(verdict, size) AS verdict FROM hits GROUP BY ALL
)
SELECT p.page_id, p.host, p.path, b.rule, coalesce(b.verdict, 'allow') AS verdict
FROM parts p LEFT JOIN best b ON p.page_id = b.page_id AND p.host = b.host AND p.path = b.path
"""
