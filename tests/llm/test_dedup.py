"""SimHash fingerprints, links and components against brute force."""

from __future__ import annotations

import random

import numpy as np
import xxhash

from thresher.llm import simhash

from .conftest import HARD


def plain_fingerprint(text, size=4):
    words = (text or "").encode().lower().split()
    grams = [b" ".join(words[k : k + size]) for k in range(max(1, len(words) - size + 1))] if words else []
    hashes = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def plain_components(prints, radius):
    values = sorted(set(prints.values()))
    root = {v: v for v in values}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, a in enumerate(values):
        for b in values[:i]:
            if (a ^ b).bit_count() <= radius:
                root[find(a)] = find(b)
    least = {}
    for d, v in prints.items():
        r = find(v)
        least[r] = min(d, least.get(r, d))
    return {d: least[find(v)] for d, v in prints.items()}


def test_hard_texts(hard, empty):
    assert simhash.digest(simhash.clusters(hard)).count() == len(HARD)
    got = simhash.digest(simhash.clusters(hard.where("doc_id is not null"))).collect()
    assert len(got) == len(HARD) - 1
    prints = {i: plain_fingerprint(t) for i, t in HARD if i is not None}
    want = plain_components(prints, 4)
    for r in got:
        assert (r.fingerprint, r.component_id) == (f"{prints[r.doc_id]:016x}", want[r.doc_id])
    assert simhash.digest(simhash.clusters(empty)).count() == 0


def test_links_lose_nothing(spark):
    """Chains of near fingerprints, with every bucket cut into chunks."""
    rng = random.Random(5)
    values = set()
    for _ in range(60):
        v = rng.getrandbits(64)
        for _ in range(12):
            values.add(v)
            for b in rng.sample(range(64), rng.randrange(1, 7)):
                v ^= 1 << b
    values = sorted(values)
    nodes = spark.createDataFrame([(bytearray(v.to_bytes(8, "big")),) for v in values], "fp binary")
    for stripes_at in (len(values), 3_000_000, 100_000_000):
        links = simhash.link(nodes, simhash.pigeonhole_keys(nodes["fp"], stripes_at, 1, 4), 1, 4, bucket=4)
        roots = {int.from_bytes(r.node, "big"): int.from_bytes(r.root, "big") for r in simhash.components(links).collect()}
        want = plain_components({v: v for v in values}, 4)
        assert {v: roots.get(v, v) for v in values} == want


def test_close_pairs_equal_plain_distances():
    rng = np.random.default_rng(3)
    for words, radius in ((1, 4), (4, 40)):
        base = rng.integers(0, 2**63, (5, words), dtype=np.uint64)
        bits = base[rng.integers(0, 5, 300)] ^ (np.uint64(1) << rng.integers(0, 64, (300, words), dtype=np.uint64))
        group = np.sort(rng.integers(0, 3, 300))
        got = {(int(a), int(b)) for i, j in simhash.close_pairs(bits, group, radius) for a, b in zip(i, j, strict=True)}
        want = {(a, b) for a in range(300) for b in range(a + 1, 300) if group[a] == group[b] and sum(int(x).bit_count() for x in bits[a] ^ bits[b]) <= radius}
        assert got == want


def test_similar_texts_are_found_and_others_stay(spark):
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))
    rows, copy_of = [], {}
    for i in range(120):
        words = [word() for _ in range(rng.randrange(150, 400))]
        rows.append((3 * i, " ".join(words)))
        if i % 2:
            for k in range(max(1, len(words) // 100)):
                words[rng.randrange(len(words))] = word()
            rows.append((3 * i + 1, " ".join(words)))
            copy_of[3 * i + 1] = 3 * i
    rows += [(1000, None), (1001, ""), (1002, ""), (None, "text"), (2000, "same"), (2001, "same")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = sorted((r.doc_id for r in simhash.keep_one(docs).collect()), key=lambda x: (x is None, x))
    gone = {i for i, _ in rows} - set(kept)
    assert gone - {2001} <= set(copy_of) and 2001 in gone
    assert len(gone - {2001}) >= 0.97 * len(copy_of)


def near_pairs(rng):
    """Pairs at Jaccard 0.8 to 0.86 over 5-word shingles, short and long, plain and repetitive; and pairs just under."""
    word = lambda: "".join(rng.choice("abcdefghij") for _ in range(6))
    for _ in range(60):
        yield (w := [word() for _ in range(8)]), [*w, word()]
        yield (w := [word() for _ in range(10)]), [*w, word()]
        w = [word() for _ in range(49)]
        yield w, [*w[:24], word(), *w[25:]]
        w = [word() for _ in range(49)]
        yield w, [*w[:20], word(), *w[21:30], word(), *w[31:]]
        w = [word() for _ in range(454)]
        yield w, [word() if k % 45 == 20 else x for k, x in enumerate(w)]
        line = [word() for _ in range(20)]
        w = [word() for _ in range(300)]
        yield w + line, w + line * 20
        yield (w := [word() for _ in range(7)]), [*w, word()]


def test_similar_pairs_are_those_of_brute_force(spark):
    rng = random.Random(31)
    pairs = list(near_pairs(rng))
    rows = [(2 * k + side, " ".join(w)) for k, p in enumerate(pairs) for side, w in enumerate(p)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    kept = {r.doc_id for r in simhash.keep_one(docs).collect()}
    want = set()
    for k, (a, b) in enumerate(pairs):
        x, y = ({tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (a, b))
        want |= {2 * k} if len(x & y) / len(x | y) >= 0.8 else {2 * k, 2 * k + 1}
    assert 60 < len(pairs) * 2 - len(want) < len(pairs)
    assert kept == want


def test_large_groups_of_near_texts_in_chunks(spark):
    """A chain in one bucket cut into chunks: neighbours are alike, the ends are not."""
    rng = random.Random(4)
    words = [f"w{k}" for k in range(400)]
    rows = []
    for k in range(30):
        rows.append((k, " ".join(words)))
        at = rng.randrange(400)
        words[at : at + 1] = [f"n{k}"]
    rows.append((99, " ".join(f"w{k}" for k in range(200))))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    prints = simhash.fingerprints(docs, 5, 4, 6)
    texts = docs.selectExpr("xxhash64(text) as mark", "text")
    keys = simhash.F.array(simhash.F.struct(simhash.F.lit(0).alias("table"), simhash.F.lit(1).alias("key")))
    links = simhash.link(prints.select("fp"), keys, 4, 256, 4, texts, 5, 0.8)
    roots = {bytes(r.node): bytes(r.root) for r in simhash.components(links).collect()}
    names = {r.doc_id: bytes(r.fp) for r in prints.select("doc_id", "fp").collect()}
    at = {k: roots.get(name, name) for k, name in names.items()}
    assert len({at[k] for k in range(30)}) == 1 and at[99] != at[0]


def test_hubs_give_the_same_components(spark, monkeypatch):
    rng = random.Random(7)
    pairs = [(0, k) for k in range(1, 60)] + [(100, k) for k in range(90, 100)] + [(k, k + 1) for k in range(200, 230)] + [(59, 205)]
    rng.shuffle(pairs)
    name = lambda k: bytearray(k.to_bytes(4, "big"))
    links = spark.createDataFrame([(name(a), name(b)) for a, b in pairs], "a binary, b binary")
    plain = {bytes(r.node): bytes(r.root) for r in simhash.components(links).collect()}
    monkeypatch.setattr(simhash, "HUB", 3)
    assert {bytes(r.node): bytes(r.root) for r in simhash.components(links).collect()} == plain
    monkeypatch.setattr(simhash, "HUBS", 1)
    assert {bytes(r.node): bytes(r.root) for r in simhash.components(links).collect()} == plain
    assert int.from_bytes(plain[bytes(name(230))], "big") == 0


def test_few_links_take_few_jobs_and_give_what_star_rounds_give(spark, monkeypatch):
    """Each star round is some ten stages that the driver plans and follows; links that fit one task need none."""
    rng = random.Random(8)
    pairs = [(0, k) for k in range(1, 60)] + [(k, k + 1) for k in range(200, 260)] + [(259, 3), (300, 301), (301, 300), (302, 302)]
    pairs += [(rng.randrange(400, 600), rng.randrange(400, 600)) for _ in range(90)] + pairs[:20]
    name = lambda k: bytearray(k.to_bytes(4, "big"))
    links = spark.createDataFrame([(name(a), name(b)) for a, b in pairs], "a binary, b binary")
    root = {k: k for pair in pairs for k in pair}
    for _ in root:
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    want = {k: r for k, r in root.items() if k != r}

    def found(jobs_of):
        spark.sparkContext.setJobGroup(jobs_of, jobs_of)
        got = simhash.components(links)
        jobs = len(spark.sparkContext.statusTracker().getJobIdsForGroup(jobs_of))
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        rows = [(int.from_bytes(r.node, "big"), int.from_bytes(r.root, "big")) for r in got.collect()]
        assert len(rows) == len(set(rows))
        return dict(rows), jobs

    got, jobs = found("few")
    assert got == want and jobs <= 6
    monkeypatch.setattr(simhash, "FEW", len(pairs) // 2)
    rounds, more = found("rounds")
    assert rounds == want and more > 3 * jobs
    monkeypatch.setattr(simhash, "HUB", 3)
    assert found("hubs")[0] == want
    assert simhash.components(links.where("a is null")).count() == 0
