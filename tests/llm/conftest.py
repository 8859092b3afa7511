import random

import pandas as pd
import pyarrow.parquet as pq
import pytest

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def prose(rng, n):
    return " ".join(rng.choice(WORDS) + rng.choice(WORDS) for _ in range(n))


def table(rows, columns):
    return pd.DataFrame({c: pd.array([r[i] for r in rows], dtype="Int64" if c in ("doc_id", "n_chars", "item_id", "quality", "toxic", "page_id") else "object") for i, c in enumerate(columns)})


@pytest.fixture(scope="session")
def odd(tmp_path_factory):
    """Documents with every odd case: nulls in any column, empty and long texts, ties, repeated rows, clashing extra columns."""
    rng = random.Random(4)
    shared = prose(rng, 90)
    line = "The  same LINE of boilerplate that many documents hold, again and again"
    texts = [prose(rng, rng.randint(5, 200)) for _ in range(60)]
    texts += [None, "", "   \n\t ", "\n\n", "Ä", "a b", "... --- !!!", "一二三 日本語", "x " * 30_000, texts[0], texts[0], texts[1].upper()]
    texts += [f"{prose(rng, 30)}\n{shared}\n{prose(rng, 30)}" for _ in range(12)]
    texts += [f"{prose(rng, 12)}\n\t{line.upper() if i % 2 else line} \n{prose(rng, 12)}\n" for i in range(9)]
    near = prose(rng, 300).split()
    for _ in range(4):
        near[rng.randrange(300)] = "changed"
        texts.append(" ".join(near))
    texts.append("# | & " * 40 + prose(rng, 20))
    langs, sources = ["en", "fr", None], ["src0", "src0", "src1", None]
    rows = [(i, t, langs[i % 3], sources[i % 4], None if t is None else len(t)) for i, t in enumerate(texts)]
    rows += [rows[3], rows[3], (None, texts[4], None, None, 3), (None, None, "en", "src0", None)]
    d = tmp_path_factory.mktemp("odd")
    docs = table(rows, ["doc_id", "text", "lang", "source", "n_chars"])
    docs["score"], docs["h1"], docs["fp"], docs["a"], docs["block"] = 1.5, "h", 7, None, "b"
    docs["a"] = docs["a"].astype("string")
    for c in ("n_lines", "n_dropped", "kept_text", "match", "shard", "slot", "size", "keys", "head", "label", "node", "anchor", "n_words", "lang_pred", "kept", "stats", "id", "key", "start", "sequence_id"):
        docs[c] = range(len(docs))
    docs.to_parquet(d / "documents.parquet")
    items = [(0, " ".join(texts[5].split()[3:20]).upper()), (1, texts[0].split()[0]), (2, None), (3, "..."), (None, prose(rng, 15)), (10, " ".join(texts[5].split()[5:22])), (10, " ".join(texts[5].split()[5:22]))]
    table(items, ["item_id", "text"]).to_parquet(d / "benchmark.parquet")
    labels = [(i, int(i % 5 > 0), 0) for i in range(50)] + [(1, None, None), (None, 1, 0), (10_000, 1, 1), (5, 1, 0)]
    table(labels, ["doc_id", "quality", "toxic"]).to_parquet(d / "labels.parquet")
    urls = ["http://Example.NET/en/x?y=1", "https://a.example.net/de/", "http://net", "http://net/", "x.org/fr/", "http://shop.org/fr/a#b", "http://example.com/de", "http://example.com/de/1", "HTTP://A.B.ORG/FR/", "http://a.net:80/", None, "", "://", "ftp://u@net/q", "http://notnet/", "http://a.com/?r=http://b.net/", "http://x.com/a.exe", "http://casino.com/", "http://x.com/?utm_source=spam", "http://x.com/net/\n", "http://é.net/é"]
    pages = [(i, u, "<p>") for i, u in enumerate(urls)] + [(0, urls[0], None), (None, urls[1], "")]
    whole = table(pages, ["page_id", "url", "html"])
    whole["rule"], whole["verdict"], whole["token"], whole["pattern"] = 1, "x", "y", "z"
    whole.to_parquet(d / "pages.parquet")
    return str(d)


@pytest.fixture(scope="session")
def empty(odd, tmp_path_factory):
    d = tmp_path_factory.mktemp("empty")
    for t in ("documents", "benchmark", "labels", "pages"):
        whole = pq.read_table(f"{odd}/{t}.parquet")
        pq.write_table(whole.slice(0, 0), d / f"{t}.parquet")
    return str(d)


@pytest.fixture(scope="session")
def odd_rows(odd):
    d = pd.read_parquet(f"{odd}/documents.parquet")
    return [(None if pd.isna(i) else int(i), None if pd.isna(t) else t) for i, t in zip(d.doc_id, d.text)]
