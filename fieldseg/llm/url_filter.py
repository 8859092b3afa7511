"""URL filters: pattern rules indexed by their rarest literal token, with DataFrame functions only.

A rule is a regular expression.  Its literal tokens, which any url that it matches must hold whole, are derived from the
expression: each branch of it has its own, and a branch without one is an error, so no match can be missed.  Tokens are counted
over all urls, and each branch is filed under its rarest one.  Distinct urls are split into tokens, tokens fetch candidate
rules, and only those run their regular expressions.  Rules about a host and path prefix come first, the longest winning; else
the rules of the method's own list decide (a block before an allow); else a page is allowed.

A null url, or one without `://`, has empty host and path, matches no rule and is allowed.  Repeated pages are judged each.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: (host, path, verdict): the given rules about hosts and their subdomains.
HOST_RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
#: (pattern, verdict): patterns over whole urls.
PATTERN_RULES = (
    (r"[?&]utm_(?:source|medium)=(?:spam|adult)", "block"),
    (r"://(?:[^/?#]*\.)?(?:casino|poker)\.", "block"),
    (r"/(?:wp-login|xmlrpc)\.php", "block"),
    (r"\.(?:exe|apk|msi)(?:[?#]|$)", "block"),
)
#: Branches that one expression may be spread into.
MOST_BRANCHES = 256
RULE_FIELDS = "rule_id int, name string, pattern string, branches array<array<string>>, verdict string, weight int"
#: Rules of this many tokens and bytes at most are broadcast; larger lists are joined by shuffle.
BROADCAST_RULES = 200_000
BROADCAST_BYTES = 32 << 20
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_LOWER_CASE = str.maketrans(UPPER, LOWER)
_TOKEN_CHARS = frozenset(LOWER + "0123456789")


def url_host(url: Column) -> Column:
    """After the first :// up to / ? # or the end, A-Z lower-cased."""
    return F.translate(F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1), UPPER, LOWER)


def url_path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def url_tokens(url: Column) -> Column:
    """Distinct runs of a-z and 0-9, with A-Z lower-cased."""
    return F.array_distinct(F.regexp_extract_all(F.translate(F.coalesce(url, F.lit("")), UPPER, LOWER), F.lit("[a-z0-9]+"), 0))


class NoToken(ValueError):
    """A rule that some url without a known literal token could match."""


#: Parts of a branch beside single letters and digits: a character that is neither or an end of the url, and anything else.
_EDGE, _ANY = "edge", "any"


def _branches(parsed) -> list[list[str]]:
    """The branches of a parsed expression, each a list of letters and digits, `_EDGE` and `_ANY`."""
    out: list[list[str]] = [[]]
    for op, arg in parsed:
        name = str(op)
        if name == "LITERAL":
            c = chr(arg).translate(_LOWER_CASE)
            # letters beyond ASCII are no part of a token, and may have a partner in ASCII where case is ignored
            parts = [[c]] if c in _TOKEN_CHARS else [[_EDGE]] if c.isascii() else [[_ANY]]
        elif name == "AT":
            # \b and its like say nothing of what is beside them
            parts = [[_EDGE if "BEGINNING" in str(arg) or "END" in str(arg) else _ANY]]
        elif name == "IN":
            parts = [[_class(arg)]]
        elif name == "SUBPATTERN":
            parts = _branches(arg[-1])
        elif name == "BRANCH":
            parts = [x for branch in arg[1] for x in _branches(branch)]
        elif name in ("MAX_REPEAT", "MIN_REPEAT", "POSSESSIVE_REPEAT"):
            least, most, body = arg
            inner = _branches(body)
            if least == most and least <= 8:
                parts = [[]]
                for _ in range(least):
                    parts = _crossed(parts, inner)
            elif (least, most) == (0, 1):
                parts = [[], *inner]
            else:
                parts = [[_EDGE]] if least and inner == [[_EDGE]] else [[_ANY]]
        elif name == "ASSERT" and all(x == [_EDGE] for x in _branches(arg[1])):
            parts = [[_EDGE]]
        else:
            parts = [[_ANY]]
        out = _crossed(out, parts)
    return out


def _class(members) -> str:
    """One letter or digit, `_EDGE` for a class without any, else `_ANY`."""
    found = set()
    for op, arg in members:
        if str(op) == "LITERAL":
            found.add(chr(arg).translate(_LOWER_CASE))
        elif str(op) == "RANGE" and arg[1] - arg[0] < 128:
            found |= {chr(c).translate(_LOWER_CASE) for c in range(arg[0], arg[1] + 1)}
        else:
            return _ANY
    if len(found) == 1 and found <= _TOKEN_CHARS:
        return found.pop()
    return _EDGE if all(c.isascii() and c not in _TOKEN_CHARS for c in found) else _ANY


def _crossed(heads: list[list[str]], tails: list[list[str]]) -> list[list[str]]:
    if len(heads) * len(tails) > MOST_BRANCHES:
        raise NoToken(f"a rule of more than {MOST_BRANCHES} branches; write it as several")
    return [h + t for h in heads for t in tails]


def required_tokens(pattern: str) -> list[list[str]]:
    """For each branch of an expression, the tokens that every url matched by it holds whole (never as a part of a longer one).

    Only what Python and Java read alike is taken: intersections of classes and Unicode flags are errors.
    """
    if "&&" in pattern or re.search(r"\(\?[a-z]*[uUd]", pattern):
        raise NoToken(f"{pattern} means another thing in Java")
    found = set()
    for branch in _branches(re._parser.parse(pattern)):
        parts, tokens, run, open_left = [_ANY, *branch, _ANY], set(), "", True
        for x in parts:
            if len(x) == 1:
                run += x
                continue
            if run and not open_left and x == _EDGE:
                tokens.add(run)
            run, open_left = "", x == _ANY
        if not tokens:
            raise NoToken(f"no literal token in a branch of {pattern}")
        found.add(tuple(sorted(tokens)))
    return [list(x) for x in sorted(found)]


def host_rule(rule_id: int, host: str, path: str, verdict: str) -> tuple:
    """A rule about a host, its subdomains and a path prefix, as a pattern over whole urls."""
    letters = "".join(f"[{c.upper()}{c}]" if c.isalpha() and c.isascii() else re.escape(c) for c in host)
    # the first :// of the url and no later one; \z is Java's very end
    pattern = rf"(?s)^(?:(?!://).)*://(?:[^/?#]*\.)?{letters}(?=[/?#]|\z)" + (re.escape(path) if path else "")
    tokens = re.findall("[a-z0-9]+", host) + (re.findall("[a-z0-9]+", path.lower().rpartition("/")[0]) if "/" in path else [])
    if not tokens:
        raise NoToken(f"no literal token in {host}{path}")
    return rule_id, host + path, pattern, [tokens], verdict, len(host + path)


def rule_table(spark: SparkSession, hosts=HOST_RULES, patterns=PATTERN_RULES) -> DataFrame:
    """(rule_id, name, pattern, branches, verdict, weight): host rules weigh by length, other patterns 0."""
    rows = [host_rule(i, *x) for i, x in enumerate(hosts)]
    rows += [(len(hosts) + i, None, p, required_tokens(p), v, 0) for i, (p, v) in enumerate(patterns)]
    return spark.createDataFrame(rows, RULE_FIELDS)


def read_rules(spark: SparkSession, rules: DataFrame) -> DataFrame:
    """The rule table of (host, path, pattern, verdict): a pattern where there is one, else a rule about a host.

    Rules come one after another to the driver, which derives their tokens, in the order of their columns.
    """
    order = ["host", "path", "pattern", "verdict"]
    rows = list(rules.select(*order).orderBy(*order).toLocalIterator())
    return rule_table(spark, [(r.host, r.path or "/", r.verdict) for r in rows if not r.pattern], [(r.pattern, r.verdict) for r in rows if r.pattern])


def rarest_token_index(urls: DataFrame, rules: DataFrame, url: str = "url", small: bool = True) -> DataFrame:
    """Rules with `token`, a row for each branch: of its literal tokens, the one in fewest urls (ties: the smallest)."""
    filed = rules.select("rule_id", F.posexplode("branches").alias("branch", "tokens")).select("rule_id", "branch", F.explode("tokens").alias("token"))
    wanted = filed.select("token").distinct()
    seen = urls.select(F.explode(url_tokens(F.col(url))).alias("token")).join(F.broadcast(wanted) if small else wanted, "token", "left_semi")
    counts = seen.groupBy("token").count()
    best = filed.join(counts, "token", "left").groupBy("rule_id", "branch").agg(F.min(F.struct(F.coalesce("count", F.lit(0)).alias("n"), "token")).alias("b"))
    # branches that share their token run the rule once
    return rules.drop("branches").join(best.select("rule_id", F.col("b.token").alias("token")).distinct(), "rule_id")


def judge_urls(pages: DataFrame, rules: DataFrame, url: str = "url") -> DataFrame:
    """(url, rule, verdict) of the distinct urls that some rule matches."""
    about = rules.agg(F.sum(F.size(F.flatten("branches"))).alias("tokens"), F.sum(F.octet_length("pattern")).alias("bytes"), F.min(F.array_min(F.transform("branches", F.size))).alias("least")).first()
    if about.least is not None and about.least < 1:
        raise NoToken("a rule needs a literal token in each branch")
    small = (about.tokens or 0) <= BROADCAST_RULES and (about.bytes or 0) <= BROADCAST_BYTES
    urls = pages.where(F.col(url).isNotNull()).select(F.col(url).alias("url")).distinct()
    index = rarest_token_index(urls, rules, "url", small)
    index = F.broadcast(index) if small else index
    candidates = urls.select("url", F.explode(url_tokens(F.col("url"))).alias("token")).join(index, "token")
    matched = candidates.where(F.expr("url rlike pattern"))
    rank = F.struct("weight", (F.col("verdict") == "block").alias("blocks"), (-F.col("rule_id")).alias("early"), "name", "verdict")
    best = matched.groupBy("url").agg(F.max(rank).alias("best"))
    return best.select("url", F.col("best.name").alias("rule"), F.col("best.verdict").alias("verdict"))


def filter_pages(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow") -> DataFrame:
    """`pages` with `rule` (null: none about the host) and `verdict`; columns of these names give way."""
    pages = pages.drop("rule", "verdict")
    judged = judge_urls(pages, rules, url).withColumnRenamed("url", "_fs_url")
    return pages.join(judged, F.col(url) == F.col("_fs_url"), "left").drop("_fs_url").withColumn("verdict", F.coalesce("verdict", F.lit(default)))


def op7(spark, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    out = filter_pages(pages, rule_table(spark))
    return out.select("page_id", url_host(F.col("url")).alias("host"), url_path(F.col("url")).alias("path"), "rule", "verdict")


OP7_SQL = r"""
with u as (
  select page_id, coalesce(url, '') as url,
    translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
    regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) as path
  from pages),
r as (
  select page_id, url, host, path, case
    when (host = 'example.com' or host like '%.example.com') and starts_with(path, '/de/') then 'example.com/de/'
    when (host = 'example.net' or host like '%.example.net') and starts_with(path, '/en/') then 'example.net/en/'
    when (host = 'org' or host like '%.org') and starts_with(path, '/fr/') then 'org/fr/'
    when (host = 'net' or host like '%.net') and starts_with(path, '/') then 'net/' end as rule
  from u)
select page_id, host, path, rule, case
  when rule in ('net/', 'example.com/de/') then 'block'
  when rule is not null then 'allow'
  when regexp_matches(url, '[?&]utm_(?:source|medium)=(?:spam|adult)') or regexp_matches(url, '://(?:[^/?#]*\.)?(?:casino|poker)\.')
    or regexp_matches(url, '/(?:wp-login|xmlrpc)\.php') or regexp_matches(url, '\.(?:exe|apk|msi)(?:[?#]|$)') then 'block'
  else 'allow' end as verdict
from r
"""
