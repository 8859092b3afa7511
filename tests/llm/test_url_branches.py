"""Every branch of every pattern rule, also where a token goes on, against the SQL."""

import random
import re

import duckdb
import pandas as pd
import pytest
from helpers import rows

from fieldseg.llm import url_filter

MATCHES = ["http://casino.com/", "http://a.poker.com/", "http://poker.org:80/x", "http://x.com/a.exe", "http://x.com/a.apk", "http://x.com/a.msi?x=1", "http://x.com/wp-login.php", "http://x.com/xmlrpc.php", "http://x.com/xmlrpc.php5", "http://x.com/wp-login.phps"]
MATCHES += [f"http://x.com/?utm_{a}={b}{c}" for a in ("source", "medium") for b in ("spam", "adult") for c in ("", "mer1")]
OTHERS = ["http://x.com/poker.html", "http://x.com/a.apks", "http://x.com/?utm_campaign=spam", "http://x.com/php", "http://x.com/A.MSI"]


def test_branches(spark, tmp_path):
    pages = pd.DataFrame({"page_id": range(len(MATCHES + OTHERS)), "url": MATCHES + OTHERS})
    pages.to_parquet(tmp_path / "pages.parquet")
    got = url_filter.op7(spark, str(tmp_path))
    with duckdb.connect() as duck:
        duck.register("pages", pages)
        assert rows(got) == rows(duck.sql(url_filter.OP7_SQL).df())
    blocked = {r.page_id for r in got.where("verdict = 'block'").collect()}
    assert blocked == set(range(len(MATCHES)))


@pytest.mark.parametrize("pattern", ["casino", r"/ads\b", "[Aa]d/", "(?:/a/|/b)", "/foo(?!bar)", "/[a-z&&[^b]]/", "(?iu)/k/", "/x*/"])
def test_rules_without_a_certain_token_are_refused(pattern):
    with pytest.raises(url_filter.NoToken):
        url_filter.required_tokens(pattern)


def test_tokens_of_branches():
    assert url_filter.required_tokens(r"^https?://spam-") == [["http", "spam"], ["https", "spam"]]
    assert url_filter.required_tokens("(?:/a/|/b/)x*/c/") == [["a", "c"], ["b", "c"]]
    assert url_filter.required_tokens("/[Aa]d{2}(?=[/?]|$)") == [["add"]]


def _random_rule(rng, names):
    some = lambda n: "|".join(rng.sample(names, n))
    return rng.choice((f"/(?:{some(3)})/(?:[0-9]+/)?{rng.choice(names)}", f"[.](?:{some(2)})(?:[/?]|$)", f"[?&]{rng.choice(names)}=(?:{some(2)})(?:&|$)", f"://(?:[^/?#]*[.])?{rng.choice(names)}[.-]", f"/{rng.choice(names)}(?:-{rng.choice(names)})?[.](?:php|asp)"))


@pytest.mark.parametrize("limit", [200_000, -1])
def test_thousands_of_rules_against_running_each(spark, tmp_path, monkeypatch, limit):
    """Rules read from a table, broadcast or shuffled, give what running every expression on every url gives."""
    monkeypatch.setattr(url_filter, "BROADCAST_RULES", limit)
    rng = random.Random(7)
    names = ["".join(rng.choice("abcdeXYz01") for _ in range(rng.randint(1, 4))) for _ in range(6000)]
    made = [(None, None, p, rng.choice(("block", "allow"))) for p in {_random_rule(rng, names) for _ in range(3000)} if _has_token(p)]
    made += [(f"{n.lower()}.org", f"/{m}/", None, "allow") for n, m in zip(rng.sample(names, 20), rng.sample(names, 20))]
    assert len(made) > 2000
    urls = [f"http://{rng.choice(names)}.{rng.choice(names)}.org/{rng.choice(names)}/{rng.choice(['', '7/'])}{rng.choice(names)}.{rng.choice(['php', 'htm', rng.choice(names)])}{rng.choice(['', '?' + rng.choice(names) + '=' + rng.choice(names)])}" for _ in range(300)]
    table = url_filter.read_rules(spark, spark.createDataFrame(made, "host string, path string, pattern string, verdict string"))
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.url: (r.rule, r.verdict) for r in url_filter.judge_urls(pages, table).collect()}
    order = sorted((r for r in made if r[2]), key=lambda r: (r[2], r[3]))
    compiled = [(re.compile(p), v) for _, _, p, v in order]
    fits = 0
    for u in urls:
        host, _, path = u[7:].partition("/")
        hosts = [(len(h + p), h + p, v) for h, p, _, v in made if h and (host.lower() == h or host.lower().endswith("." + h)) and ("/" + path).startswith(p)]
        hit = {v for p, v in compiled if p.search(u)}
        if hosts:
            assert got[u] == max(hosts)[1:]
        else:
            assert got.get(u, (None, None))[1] == ("block" if "block" in hit else "allow" if hit else None)
        fits += bool(hit)
    assert 20 < fits < 295


def _has_token(pattern):
    try:
        return bool(url_filter.required_tokens(pattern))
    except url_filter.NoToken:
        return False
