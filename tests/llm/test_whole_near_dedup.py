"""The near-duplicate stage finds every pair of the similarity, at every size of a group, whatever the texts differ in."""

import random

import brute
import pytest

from fieldseg.llm import simhash


def text(rng, n):
    return [f"w{rng.randrange(5000)}" for _ in range(n)]


def survivors(spark, texts, **how):
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return sorted(r.doc_id for r in simhash.near_dedup(docs, **how).select("doc_id").collect())


def expected(texts):
    return sorted(i for i, _ in brute.near_survivors(list(enumerate(texts))))


def test_partner_of_any_member_of_a_large_group(spark):
    """700 copies of one text with four words of their own appended, and texts that are near one of them alone."""
    rng = random.Random(1)
    base = text(rng, 60)
    members = [[*base, *(f"own{i}.{k}" for k in range(4))] for i in range(700)]
    hung = [[*m[8:], *text(rng, 2)] for m in members[::20]]
    texts = [" ".join(t) for t in members + hung]
    assert survivors(spark, texts) == [0]


def test_any_size_of_a_run(spark):
    """Pairs on the limit that share common windows with many texts that aren't near them."""
    rng = random.Random(2)
    common = text(rng, 24)
    texts = []
    for i in range(150):
        own = text(rng, 60)
        texts.append(" ".join(common + own))
        if i % 3 == 0:
            texts.append(" ".join(common + own[:50] + text(rng, rng.choice((1, 4, 7, 10)))))
    want = expected(texts)
    assert len(want) < len(texts) and survivors(spark, texts) == want


@pytest.mark.parametrize("edit", ["cut", "extended", "paragraph", "scattered"])
def test_recall_of_edits(spark, edit):
    """Copies between 0.8 and 0.9, by contiguous edits and by scattered ones: no pair is missed and none is made up."""
    rng = random.Random(edit)
    texts = []
    for _ in range(120):
        a = text(rng, rng.randint(60, 300))
        n, share = len(a), rng.uniform(0.02, 0.2)
        k = max(1, int(n * share))
        at = rng.randrange(n - k)
        if edit == "cut":
            b = a[: n - k]
        elif edit == "extended":
            b = a + text(rng, k)
        elif edit == "paragraph":
            b = a[:at] + text(rng, k // 2 + 1) + a[at + k // 2 + 1 :]
        else:
            b = [x if rng.random() > share / 8 else "changed" for x in a]
        texts += [" ".join(a), " ".join(b)]
    want = expected(texts)
    assert len(texts) - len(want) > 40 and survivors(spark, texts) == want


def test_the_order_of_windows_changes_nothing(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = sorted(r.doc_id for r in simhash.near_dedup(docs).select("doc_id").collect())
    monkeypatch.setattr(simhash, "COMMON_COUNT", 1 << 30)
    monkeypatch.setattr(simhash, "leader_pairs", lambda nodes: nodes.select(nodes.node.alias("a"), nodes.node.alias("b")).limit(0))
    assert sorted(r.doc_id for r in simhash.near_dedup(docs).select("doc_id").collect()) == got


def test_long_runs_are_compared_like_short_ones(spark, sf, monkeypatch):
    monkeypatch.setattr(simhash, "leader_pairs", lambda nodes: nodes.select(nodes.node.alias("a"), nodes.node.alias("b")).limit(0))
    rng = random.Random(3)
    base = text(rng, 80)
    texts = [" ".join(x if rng.random() > 0.02 else "changed" for x in base) for _ in range(200)]
    assert survivors(spark, texts) == expected(texts)


def test_many_ends_are_fetched_by_shuffle(spark, sf, monkeypatch):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = sorted(r.doc_id for r in simhash.near_dedup(docs).select("doc_id").collect())
    monkeypatch.setattr(simhash, "BROADCAST_ENDS", -1)
    assert sorted(r.doc_id for r in simhash.near_dedup(docs).select("doc_id").collect()) == got


def test_parity_rules_out_no_similar_pair(spark):
    """The bits that differ are no more than the windows that one text alone has."""
    rng = random.Random(6)
    pairs = []
    for i in range(200):
        a = text(rng, rng.randint(1, 400))
        b = [x if rng.random() > 0.03 else "changed" for x in a] + text(rng, rng.randrange(5))
        pairs += [(2 * i, " ".join(a)), (2 * i + 1, " ".join(b))]
    docs = spark.createDataFrame(pairs, "doc_id long, text string")
    none = (simhash.np.zeros(0, simhash.np.uint64), simhash.np.zeros(0, simhash.np.int64))
    got = {r.doc_id: r.parity for r in simhash.digests(docs, "text", [docs.doc_id.alias("n1"), docs.doc_id.alias("n2")], 5, 0.8, none).collect()}
    for i in range(200):
        a, b = ({tuple(t.split()[k : k + 5]) for k in range(max(1, len(t.split()) - 4))} for _, t in pairs[2 * i : 2 * i + 2])
        assert sum(((x ^ y) & (1 << 64) - 1).bit_count() for x, y in zip(got[2 * i], got[2 * i + 1])) <= len(a ^ b)


def test_held_pairs_are_all_sent():
    """Each pair comes out at least once, and one that repeats while it is held comes out once."""
    rng = random.Random(8)
    held, sent, put = simhash._Pairs(), [], set()
    for _ in range(60):
        a, b = ([rng.randrange(40) for _ in range(30)] for _ in range(2))
        held.add(simhash.np.array(a), simhash.np.array(b))
        put |= {(min(p), max(p)) for p in zip(a, b)}
        sent += map(tuple, held.full(200).tolist())
    sent += map(tuple, held.full(-1).tolist())
    assert set(sent) == put
    held.add(simhash.np.array([1, 2, 1]), simhash.np.array([2, 1, 2]))
    assert held.full(-1).tolist() == [[1, 2]] and not len(held.full(-1))


def nothing(nodes, *_):
    return nodes.select(nodes.node.alias("a"), nodes.node.alias("b")).limit(0)


def test_fingerprints_alone_link_texts_within_two_bits(spark, monkeypatch):
    """Without leaders and the exact search, SimHash and its Golay keys join the long texts that differ in a word at the end."""
    monkeypatch.setattr(simhash, "leader_pairs", nothing)
    monkeypatch.setattr(simhash, "prefix_pairs", nothing)
    rng = random.Random(9)
    texts = []
    for _ in range(20):
        t = text(rng, 1500)
        texts += [" ".join(t), " ".join([*t, "more"])]
    fps = [int(simhash.majority(simhash.np.array(h, simhash.np.uint64), simhash.np.zeros(len(h), int), 1)[0]) for h in (simhash.shingle_hashes(t.encode()) for t in texts)]
    near = [i for i in range(0, 40, 2) if (fps[i] ^ fps[i + 1]).bit_count() <= 2]
    assert len(near) > 10
    assert survivors(spark, texts) == [i for i in range(40) if i - 1 not in near]


def test_simhash_pairs_join_what_two_bits_join(spark):
    """Components by every pair of fingerprints, with equal ones, chains and far ones."""
    rng = random.Random(10)
    fps = []
    for _ in range(30):
        f = rng.getrandbits(64)
        for _ in range(rng.randint(1, 5)):
            fps.append(f)
            f ^= sum(1 << b for b in rng.sample(range(64), rng.choice((0, 1, 2, 3))))
    rows = [(1000 + i, f - (1 << 64) if f >> 63 else f) for i, f in enumerate(fps)]
    got = [(r.a - 1000, r.b - 1000) for r in simhash.simhash_pairs(spark.createDataFrame(rows, "node long, fp long")).collect()]
    want = brute.components(len(fps), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 2)
    linked = set(got)
    assert brute.components(len(fps), lambda a, b: (a, b) in linked or (b, a) in linked) == want


def test_linked_fingerprints_are_checked_by_windows(spark):
    """A line that repeats outweighs all else in a fingerprint, but the texts around it differ and both stay."""
    rng = random.Random(11)
    texts = [" ".join([*["over and over"] * 400, *text(rng, 40)]) for _ in range(3)]
    assert len({simhash.majority(simhash.np.array(h, simhash.np.uint64), simhash.np.zeros(len(h), int), 1)[0] for h in map(simhash.shingle_hashes, map(str.encode, texts))}) == 1
    assert survivors(spark, texts) == [0, 1, 2]
