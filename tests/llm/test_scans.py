"""Decontamination, license rules, toxicity, chat roles, sharding, top-k and language model."""

from __future__ import annotations

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from thresher.llm import chat, decontaminate, licenses, maxent, mtree, shard, toxicity
from thresher.llm.common import blank_words, plain_words

from .conftest import HARD


def plain_scan(docs, items, width=10):
    windows = {}
    for name, text in items:
        w = plain_words(text)
        n = min(width, len(w))
        for k in range(len(w) - n + 1 if n else 0):
            windows.setdefault(tuple(w[k : k + n]), set()).add(str(name))
    out = []
    for i, text in docs:
        w = plain_words(text)
        hit, names = set(), set()
        for length in {len(x) for x in windows}:
            for k in range(len(w) - length + 1):
                if found := windows.get(tuple(w[k : k + length])):
                    hit.update(range(k, k + length))
                    names |= found
        out.append((i, len(w), len(hit), len(names), hashlib.sha256(",".join(sorted(names)).encode()).hexdigest(), bool(hit)))
    return sorted(out, key=str)


@pytest.mark.parametrize("block_words", [4_000_000, 5])
def test_decontamination(spark, hard, empty, block_words):
    items = [(1, "two three four five six seven eight nine ten eleven"), (2, "mat THE cat"), (10, "x"), (11, None), (12, ""), (3, "x"), (None, "a row")]
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    got = sorted((tuple(r) for r in decontaminate.scan(hard, benchmark, block_words=block_words).collect()), key=str)
    assert got == plain_scan(HARD, [x for x in items if x[0] is not None])
    assert decontaminate.scan(empty, benchmark).count() == 0
    assert decontaminate.scan(hard, benchmark.where("false")).where("contaminated").count() == 0


@pytest.mark.parametrize("block_words", [500_000, 8])
def test_item_ids_of_any_text(spark, block_words):
    items = [("a,b", "one two three"), ("", "four five six"), ("c", "seven eight")]
    docs = [(1, "one two three x four five six"), (2, "seven eight"), (3, None)]
    got = decontaminate.scan(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id string, text string"), block_words=block_words).collect()
    assert sorted((tuple(r) for r in got), key=str) == plain_scan(docs, items)


def test_blocks_cut_what_one_block_cuts(spark):
    """Windows that overlap, and windows that only meet once something between them has gone."""
    rng = random.Random(3)
    items = [(k, " ".join(rng.choice("abcd") for _ in range(rng.randrange(3, 7)))) for k in range(6)]
    docs = [(k, " ".join(rng.choice("abcd") for _ in range(40)), k) for k in range(30)] + [(99, None, 1), (98, "", 2), (97, "z Z", 3)]
    table, bench = spark.createDataFrame(docs, "doc_id long, text string, row int"), spark.createDataFrame(items, "item_id long, text string")
    one = {r.doc_id: (r.text, r.row) for r in decontaminate.clean(table, bench, "spans", width=4).collect()}
    more = decontaminate.clean(table, bench, "spans", width=4, block_words=4)
    assert more.columns == table.columns and {r.doc_id: (r.text, r.row) for r in more.collect()} == one
    left = decontaminate.scan(more, bench, width=4).where("contaminated").count()
    assert left == 0 and sum(t != dict((a, b) for a, b, _ in docs)[i] for i, (t, _) in one.items()) > 5


def test_spans_and_documents_go(spark, hard):
    benchmark = spark.createDataFrame([(1, "two three four five six seven eight nine ten eleven")], "item_id long, text string")
    kept = decontaminate.clean(hard, benchmark, "documents")
    assert kept.columns == hard.columns and {r.doc_id for r in kept.collect()} == {i for i, _ in HARD} - {4, 5}
    more = benchmark.unionByName(spark.createDataFrame([(2, "naïve")], "item_id long, text string"))
    assert {r.doc_id for r in decontaminate.clean(hard, more, block_words=3).collect()} == {i for i, _ in HARD} - {4, 5, 7}
    cut = {r.doc_id: r.text for r in decontaminate.clean(hard, benchmark, "spans").collect()}
    assert cut[4] == "One  twelve." and cut[1] is None and cut[6] == HARD[6][1]


def test_licenses(hard, empty):
    got = {r.doc_id: r for r in licenses.scan(hard).collect()}
    assert licenses.scan(hard).count() == len(HARD)
    for i, text in HARD:
        w = [x.decode() for x in plain_words(text)]
        places = [(k, label) for phrase, label in licenses.BASE.items() for p in [phrase.split()] for k in range(len(w)) if w[k : k + len(p)] == p]
        r = got[i]
        assert (r.n_words, r.n_base) == (len(w), len(places)), i
        assert r.base_labels == ",".join(sorted({x for _, x in places}))
        assert (r.first_word, r.last_word) == ((min(places)[0], max(places)[0]) if places else (None, None))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1
    assert licenses.scan(empty).count() == 0
    assert len(licenses.rules()) > 300


def plain_detections(norm, rules):
    """Every rule over the whole text, then suppression by comparing all pairs."""
    import re

    found = set()
    for r in rules:
        if f" {r.keyword} " not in norm:
            continue
        for m in re.finditer(r.pattern, norm):
            first = norm[: m.start()].count(" ")
            found.add((first, first + m[0].count(" ") - 1, r.priority, -r.confidence, r.label))
    kept = []
    for a in found:
        inside = any(b[2] < a[2] and b[0] <= a[0] and a[1] <= b[1] for b in found)
        lesser = any(b[:2] == a[:2] and b[2:] < a[2:] for b in found)
        if not inside and not lesser:
            kept.append((a[4], a[0], a[1]))
    return sorted(kept)


def test_every_rule_is_found_and_suppression_equals_all_pairs(spark):
    rules = licenses.rules()
    handwritten = [line.split("|", 1) for line in licenses.PASSAGES.strip().splitlines()]
    assert len(handwritten) > 150 and len({p for _, p in handwritten}) == len(handwritten) and len(rules) > 700
    rng = random.Random(4)
    pool = [" ".join(p.split()) for _, p in handwritten if all(w.isalnum() for w in p.split())]
    names = [n for _, some, short, _ in licenses.FAMILIES for n in some + short]
    texts = []
    for k in range(120):
        parts = [rng.choice([rng.choice(pool), f"licensed under the {rng.choice(names)} version 2 0", f"spdx license identifier {rng.choice(names)}", rng.choice(names), "some other words"]) for _ in range(rng.randrange(1, 5))]
        texts.append(" " + " ".join(parts) + " ")
    texts += [f" {p} " for p in pool]
    docs = spark.createDataFrame(list(enumerate(texts)), "row long, norm string")
    got = {}
    for r in licenses.detections(docs).collect():
        got.setdefault(r.row, []).append((r.label, r["first"], r["last"]))
    for k, norm in enumerate(texts):
        assert sorted(got.get(k, [])) == plain_detections(norm, rules), norm
    for k, p in enumerate(pool):
        assert got[120 + k], p
    whole = {r.doc_id: r for r in licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for k, norm in enumerate(texts):
        base = {label for phrase, label in licenses.BASE.items() if f" {phrase} " in norm}
        assert whole[k].labels == ",".join(sorted(base | {x[0] for x in plain_detections(norm, rules)}))


def test_priority_suppresses_what_lies_inside(spark):
    rules = [licenses.Rule("b", " a b c(?= )", "long", 1, 0.9), licenses.Rule("b", " b(?= )", "short", 2, 0.8), licenses.Rule("b", " c d(?= )", "over", 2, 0.7), licenses.Rule("b", " a b c(?= )", "twin", 3, 0.7)]
    docs = spark.createDataFrame([(1, " a b c d b ")], "row long, norm string")
    # The gate asks for the keyword's longest word.
    found = sorted((r.label, r["first"], r["last"]) for r in licenses.detections(docs, rules).collect())
    assert found == [("long", 0, 2), ("over", 2, 3), ("short", 4, 4)]


def test_toxicity_learns_and_ignores_the_rest(spark, hard, empty):
    rng = random.Random(2)
    common = ["".join(rng.choice("aeiou") for _ in range(4)) for _ in range(80)]
    rows, labels = [], []
    for i in range(600):
        words = [rng.choice(common) for _ in range(60)]
        toxic = i % 6 == 0
        if toxic:
            words[5] = words[20] = rng.choice(["grubbly", "snarkon"])
        rows.append((i, " ".join(words)))
        labels.append((i, int(toxic)))
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([*labels, (None, 1), (9999, None)], "doc_id long, toxic int")
    got = {r.doc_id: r for r in toxicity.digest(docs, marks).collect()}
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i, r in got.items())
    assert np.mean([got[i].predicted == t for i, t in labels if got[i].held_out]) > 0.99
    scored = toxicity.score(hard, marks)
    assert scored.count() == len(HARD) and "document_score" in scored.columns
    assert {r.document_score for r in scored.collect()} == {2.0}
    kept = toxicity.keep_clean(hard, marks)
    assert kept.columns == hard.columns and {r.score for r in kept.collect()} <= {2.0}
    assert toxicity.score(empty, marks).count() == 0 and toxicity.keep_clean(empty, marks).count() == 0
    assert {r.score for r in toxicity.score(hard, marks.where("false")).collect()} == {0.0}


def test_toxicity_labels_do_not_depend_on_partitions(spark):
    rows = [(i, f"word{i % 4} other text {'bad' if i % 4 == 0 else 'good'}") for i in range(60)]
    marks = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, toxic int")
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = [sorted((r.doc_id, round(r.score, 9)) for r in toxicity.score(docs.repartition(n), marks.repartition(n)).collect()) for n in (1, 4, 7)]
    assert got[0] == got[1] == got[2]
    one = toxicity.training_rows(docs, marks).collect()
    assert len(one) == 4 and all(0 <= r.toxic <= r.n for r in one) and sum(r.n for r in one) == sum(zlib.crc32(str(i).encode()) % 5 != 0 for i in range(60))


def test_toxicity_sample_counts_ids_not_label_rows(spark):
    docs = spark.createDataFrame([(i, f"text number {i}") for i in range(400)], "doc_id long, text string")
    marks = spark.createDataFrame([(i, 0) for i in range(400) for _ in range(8)], "doc_id long, toxic int")
    assert toxicity.training_rows(docs, marks, 100).count() == 100


def test_toxicity_scores_equal_dense_cosines(spark):
    """The whole query against a plain version: all words, dense vectors, the nearest by a full sort."""
    rng = random.Random(12)
    vocabulary = [f"{a}{b}o" for a in "bcdfglmnprst" for b in "aeiou"]
    rows = [(i, " ".join(rng.choice(vocabulary) for _ in range(30)) + (" grubbly grubber" if i % 5 == 0 else "")) for i in range(300)]
    marks = [(i, int(i % 5 == 0)) for i, _ in rows]
    docs, labels = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(marks, "doc_id long, toxic int")
    scorer = toxicity.fit(docs, labels)
    finder, index = scorer.finder(), scorer.index
    size = len(scorer.words) + len(scorer.chosen)

    def dense(text):
        out = np.zeros(size)
        words = plain_words(text)
        for k, w in enumerate(scorer.words):
            if n := words.count(w):
                out[k] = 1 + math.log(n)
        for k, t in enumerate(scorer.chosen):
            hits = [w for w in words if w.decode()[: len(t) - 1] == t[1:].decode()]
            n = len(set(hits)) if t[:1] == b"2" else len(hits)
            if n and (t[:1] == b"^" or n > 1):
                out[len(scorer.words) + k] = 1 + math.log(n)
        out *= index.weight
        return out / (np.linalg.norm(out) or 1)

    df = {w: sum(w in plain_words(t) for _, t in rows) for w in scorer.words}
    assert any(math.isclose(index.weight[k], math.log(301 / (1 + df[w])) + 1) for k, w in enumerate(scorer.words))
    texts = {i: t for i, t in rows}
    examples = np.array([dense(texts[i]) for i in index.names])
    got = {r.doc_id: r.score for r in toxicity.score(docs, labels).collect()}
    for i, t in rows[:60]:
        cosines = examples @ dense(t)
        best = sorted(range(len(cosines)), key=lambda n: (-round(cosines[n], 12), n))[: toxicity.K]
        votes = cosines[best] ** 2
        want = ((votes * index.toxic[best]).sum() + index.share * toxicity.SHARE_WEIGHT) / (votes.sum() + toxicity.SHARE_WEIGHT)
        assert math.isclose(got[i], want, rel_tol=1e-6), i
        assert [n for _, n in index.nearest(*finder.of(t))] == best


def test_block_max_search_is_exact():
    rng = np.random.default_rng(4)
    examples = []
    for k in range(500):
        terms = np.sort(rng.choice(12, rng.integers(1, 6), replace=False)).astype(np.int64)
        examples.append((terms, rng.integers(1, 4, len(terms)), 1, int(rng.integers(0, 2)), k))
    index = toxicity.BlockMaxIndex(1 + rng.random(12), examples)
    assert index.n == 500 and index.blocks == 8
    own = dict(zip(index.names, range(500), strict=True))
    matrix = np.zeros((500, 12))
    for terms, times, _, _, k in examples:
        matrix[own[k], terms] = index.vector(terms, times)[1]
    for terms, times, *_ in examples[:40]:
        q = np.zeros(12)
        q[terms] = index.vector(terms, times)[1]
        cosines = matrix @ q
        want = sorted(range(500), key=lambda n: (-round(cosines[n], 12), n))[: toxicity.K]
        assert [n for _, n in index.nearest(terms, times)] == want


def test_index_is_laid_out_once(monkeypatch):
    """The driver holds one index of all examples, not the unordered one before it as well."""
    rng = np.random.default_rng(6)
    examples = []
    for k in range(3 * toxicity.BLOCK):
        terms = np.unique(rng.integers(0, 300, rng.integers(1, 9)))
        examples.append((terms, np.ones(len(terms), np.int64), 1, k % 2, k))
    built, build = [], toxicity.BlockMaxIndex._build
    monkeypatch.setattr(toxicity.BlockMaxIndex, "_build", lambda self, own: (built.append([x[4] for x in own]), build(self, own))[1])
    index = toxicity.BlockMaxIndex(1 + rng.random(300), examples)
    assert [len(x) for x in built].count(len(examples)) == 1 and index.names == built[-1]
    pivots = next(x for x in built if x and len(x) < len(examples))
    order = sorted(range(len(examples)), key=lambda k: (examples[k][0].tolist(), str(k)))
    assert pivots == order[:: -(-len(examples) // toxicity.PIVOTS)]


def test_chat_roles(spark):
    marked = "System: be kind\n\nUser: what is it?\nAssistant: it is a thing.\nmore of it\n\nHuman: ok\n### Assistant\nfine"
    model = chat.RoleModel({})
    docs = spark.createDataFrame([(1, marked), (2, None), (3, "")], "conv_id long, text string")
    got = chat.parse_transcripts(docs, model).orderBy("conv_id", "turn").collect()
    assert [r.role_found for r in got] == ["system", "user", "assistant", "user", "assistant"]
    assert got[2].rendered == "<|assistant|>\nit is a thing.\nmore of it\n<|end|>\n" and got[4].rendered == "<|assistant|>\nfine\n<|end|>\n"
    turns = [(c, t, ("user", "assistant")[t % 2], "short?" if t % 2 == 0 else "a long answer of many words\nand lines.") for c in range(40) for t in range(4)]
    table = spark.createDataFrame([*turns, (None, None, None, None), (7, 1, "assistant", None)], "conv_id long, turn long, role string, text string")
    found = chat.digest(table)
    truth = {(c, t): r for c, t, r, _ in turns}
    rows = found.collect()
    assert len(rows) == len(turns) + 2 and all(truth[r.conv_id, r.turn] == r.role_found for r in rows if r.conv_id is not None and (r.conv_id, r.turn) != (7, 1))
    assert chat.digest(table.where("false")).count() == 0


def test_viterbi_is_the_best_path():
    rng = np.random.default_rng(1)
    model = chat.RoleModel({("start", "", "user"): 3, ("next", "user", "assistant"): 5, ("next", "assistant", "user"): 4})
    for _ in range(20):
        e = rng.normal(size=(5, 3))
        score = lambda p: model.start[p[0]] + e[0][p[0]] + sum(model.next[a, b] + e[k + 1][b] for k, (a, b) in enumerate(zip(p, p[1:])))  # noqa: E731, B023, B905
        every = [(a, b, c, d, f) for a in range(3) for b in range(3) for c in range(3) for d in range(3) for f in range(3)]
        assert tuple(model.viterbi(e)) == max(every, key=score)


def test_long_transcripts_are_decided_as_if_whole(spark, monkeypatch):
    rng = np.random.default_rng(5)
    model = chat.RoleModel({("start", "", "user"): 3, ("next", "user", "assistant"): 5, ("next", "assistant", "user"): 4})
    for n in (1, 2, 50, 400):
        for scale in (0.05, 1.0):
            emissions = rng.normal(size=(n, 3)) * scale
            score, back = model.start + emissions[0], []
            for e in emissions[1:]:
                step = score[:, None] + model.next
                back.append(step.argmax(0))
                score = step.max(0) + e
            want = [int(score.argmax())]
            for pointers in reversed(back):
                want.append(int(pointers[want[-1]]))
            path, got = chat.Path(model), []
            for e in emissions:
                path.add(e)
                if rng.random() < 0.2:
                    got += path.decided()
            assert got + path.rest() == want[::-1]
    monkeypatch.setattr(chat, "SETTLE", 4)
    turns = [(c, t, f"line {t}{'?' if t % 2 else '.'}", "assistant", 3) for c in (1, 2, None) for t in range(50)] + [(1, 50, "word " * 40_000, "x", 1)]
    table = spark.createDataFrame(turns, "conv_id long, turn long, text string, row string, role_found int")
    small = sorted(map(str, chat.roles(table, model).collect()))
    monkeypatch.setattr(chat, "SETTLE", 1 << 10)
    assert small == sorted(map(str, chat.roles(table, model).collect())) and len(small) == len(turns)


def test_roles_equal_a_plain_version(spark):
    """The whole query: counts, emissions and paths, transcript by transcript; null ids stand alone."""
    rng = random.Random(9)
    rows = [(c, t, rng.choice(chat.ROLES), rng.choice(["Why?", "Because of this.", "User: hi", "be kind\n- a\n- b", ""])) for c in [*range(30), None] for t in range(4)]
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    counts = Counter()
    trained = [r for r in rows if zlib.crc32((str(r[0]) if r[0] is not None else "").encode()) % 5 != 0]
    for c in range(30):
        own = [r for r in trained if r[0] == c]
        counts.update([("start", "", own[0][2])] if own else [])
        counts.update(("next", a[2], b[2]) for a, b in zip(own, own[1:], strict=False))
    counts.update(("start", "", r[2]) for r in trained if r[0] is None)
    counts.update(("see", r[2], v) for r in trained for v in chat.features(r[3]))
    model = chat.RoleModel(dict(counts))
    want = Counter()
    for c in range(30):
        own = [r for r in rows if r[0] == c]
        want.update((r[0], r[1], chat.ROLES[k]) for r, k in zip(own, model.viterbi([model.emission(r[3]) for r in own]), strict=True))
    want.update((None, r[1], chat.ROLES[model.viterbi([model.emission(r[3])])[0]]) for r in rows if r[0] is None)
    assert Counter((r.conv_id, r.turn, r.role_found) for r in chat.digest(table).collect()) == want


def test_sharding(spark, hard, empty):
    got = shard.assign(hard).collect()
    assert len(got) == len(HARD)
    sizes = Counter((i, len((t or "").encode()) + 16, zlib.crc32((t or "").encode())) for i, t in HARD)
    assert Counter((r.doc_id, r["size"], r.text_crc32) for r in got) == sizes
    rows = [(i, "hot text " * 10 if i % 3 == 0 else f"{i} " * (i % 50 + 1)) for i in range(6000)]
    got = shard.assign(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    load, slots = Counter(), {}
    for r in got:
        load[r.shard] += r["size"]
        slots.setdefault(r.shard, []).append(r.slot)
    assert set(load) == set(range(40)) and max(load.values()) - min(load.values()) < 0.05 * max(load.values())
    assert all(sorted(s) == list(range(len(s))) for s in slots.values())
    assert shard.assign(empty).count() == 0


def test_dealt_files_hold_every_row_in_order(spark, tmp_path):
    rows = [(None if i % 7 == 0 else i % 500, "hot" if i % 3 == 0 else f"text {i}", f"s{i}", -i) for i in range(2000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, shard string, slot int")
    path = str(tmp_path / "shards")
    shard.deal(docs.repartition(5), path, 8, block_rows=50)
    found = spark.read.parquet(path).select("shard", "slot", "slot_block", "own.*")
    got = found.toDF("to", "at", "block", *docs.columns).collect()
    assert Counter((r.doc_id, r.text, r.shard, r.slot) for r in got) == Counter(rows)
    slots = {}
    for r in got:
        slots.setdefault(r.to, []).append(r.at)
        assert r.block == r.at // 50
    assert set(slots) == set(range(8)) and all(sorted(s) == list(range(len(s))) for s in slots.values())


def test_shards_equal_a_plain_version(spark):
    """Groups of equal texts stay together unless they are beyond what a shard has left; sizes are near equal."""
    rng = random.Random(1)
    rows = [(i, rng.choice(["a" * 300, "b" * 50, f"{i}" * rng.randrange(1, 40)])) for i in range(5000)]
    got = {r.doc_id: r for r in shard.assign(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    load, homes = Counter(), {}
    for i, t in rows:
        assert (got[i]["size"], got[i].text_crc32, got[i].law, got[i].grown_shard) == (len(t) + 16, zlib.crc32(t.encode()), "bytes", None)
        load[got[i].shard] += len(t) + 16
        homes.setdefault(t, set()).add(got[i].shard)
    share = sum(load.values()) / 40
    assert len(load) == 40 and all(abs(x - share) < share / 50 + 320 for x in load.values())
    split = [t for t, h in homes.items() if len(h) > 1]
    assert len(split) <= 40 and all(len(h) <= 2 + sum(len(t) + 16 for _, x in rows if x == t) / share for t, h in homes.items())


def test_exact_top_k(spark):
    rng = np.random.default_rng(8)
    x = rng.normal(size=(400, 8)).round(1)
    x[100:250] = x[100]
    rows = [(i, v.tolist(), 1) for i, v in enumerate(x)] + [(1000, None, 1), (1050, [1.0, None] + [0.0] * 6, 1), (1100, [float("nan")] + [0.0] * 7, 1), (1150, [float("inf")] + [0.0] * 7, 1), (None, [0.0] * 8, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, score int")
    got = mtree.top_k(df, df["vec_id"] % 50 == 0, shard_rows=90, block_rows=3).collect()
    q = np.floor(256 * x).astype(int)
    for me in range(0, 400, 50):
        want = sorted((-int(q[me] @ q[i]), i) for i in range(400) if i != me)[:5]
        assert [(-r.score, r.vec_id) for r in sorted((r for r in got if r.query_id == me), key=lambda r: r.rank)] == want
    assert len(got) == 40 and mtree.top_k(df.where("false"), df["vec_id"] % 50 == 0).count() == 0


def test_tree_search_is_exact_and_its_bounds_spare_products(monkeypatch):
    """Many levels: bounds and parent distances must not lose a tie."""
    monkeypatch.setattr(mtree, "PAGE", 8)
    monkeypatch.setattr(mtree, "FANOUT", 4)
    rng = np.random.default_rng(2)
    x = np.floor(rng.normal(size=(600, 3)) * 6)
    ids = rng.permutation(600)
    root, center = mtree.build(x, ids)
    depth = lambda n: 1 if n.children is None else 1 + max(map(depth, n.children))
    assert depth(root) > 3
    want = [sorted((-int(x[k] @ v), int(i)) for v, i in zip(x, ids, strict=True) if i != ids[k])[:5] for k in range(60)]
    best, computed = mtree.search(root, center, x[:60], ids[:60], 5)
    assert best.found == want and computed < 60 * 600 / 2
    floors = np.array([-w[-1][0] for w in want], float)
    again, fewer = mtree.search(root, center, x[:60], ids[:60], 5, floors)
    assert again.found == want and fewer < computed
    for k in (0, 17):
        assert mtree.search(root, center, x[k : k + 1], ids[k : k + 1], 5)[0].found == [want[k]]


def test_products_beyond_floats_are_whole_numbers(spark):
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.integers(-(2**22), 2**22, (120, 6)).astype(float), np.full((2, 6), 2.0**22 - 1)])
    x[60:90] = x[0] + rng.integers(0, 2, (30, 6)) / 256
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    whole = [[int(np.floor(256 * c)) for c in v] for v in x]
    for rows in (30, 1000):
        got = mtree.top_k(df, df["vec_id"] % 50 == 0, shard_rows=rows, block_rows=2).collect()
        for me in (0, 50, 100):
            want = sorted((-sum(a * b for a, b in zip(whole[me], v, strict=True)), i) for i, v in enumerate(whole) if i != me)[:5]
            assert [(-r.score, r.vec_id) for r in sorted((r for r in got if r.query_id == me), key=lambda r: r.rank)] == want


def test_language_model(spark, hard, empty):
    rng = random.Random(3)
    a, b = [f"{x}ing" for x in "abcdefgh"], [f"{x}eau" for x in "stuvwxyz"]
    rows = [(i, " ".join(rng.choice((a, b)[i % 2]) for _ in range(50))) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = maxent.digest(docs).collect()
    train = Counter(w for i, t in rows if zlib.crc32(str(i).encode()) % 7 != 2 for w in [*blank_words(t), maxent.END])
    n, v = sum(train.values()), len(train)
    for r in got:
        words = [*blank_words(dict(rows)[r.doc_id]), maxent.END]
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(words), sum(w in train for w in words), n)
        assert math.isclose(r.base_score, sum(math.log10((train[w] + 1) / (n + v + 1)) for w in words), rel_tol=1e-9)
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 7 == 2)
    held = [r for r in got if r.held_out]
    assert sum(r.score for r in held) > 0.8 * sum(r.base_score for r in held)
    assert maxent.digest(hard).count() == len(HARD) and maxent.digest(empty).count() == 0


def small_vocabulary(n_head=90, n_tail=40):
    """Head and tail words with their counts, END in front, and the endings that hold them all."""
    head = [(maxent.END, 200), *((f"w{k}{'aeiou'[k % 5]}n".encode(), 150 - k) for k in range(n_head))]
    tails = {f"t{k}zz".encode(): 1 + k % 3 for k in range(n_tail)}
    endings: dict[bytes, list[int]] = {}
    for w, c in [*head, *tails.items()]:
        e = endings.setdefault(maxent.ending(w), [0, 0])
        e[0] += c
        e[1] += 1
    total = sum(c for _, c in head) + sum(tails.values())
    ordered = sorted(((e, c, n) for e, (c, n) in endings.items()), key=lambda x: -x[1])
    return maxent.Vocabulary(head, ordered, total, len(head) + n_tail), [w for w, _ in head], tails


def random_model(vocabulary, seed=0):
    rng = np.random.default_rng(seed)
    return maxent.Model(vocabulary, rng.normal(size=(maxent.ROWS, maxent.CLASSES)).astype(np.float32), rng.normal(size=(maxent.INNER_ROWS, maxent.SLOTS)).astype(np.float32))


def test_word_probabilities_add_up():
    vocabulary, head, tails = small_vocabulary()
    assert set(vocabulary.slots[vocabulary.classes >= maxent.OWN].tolist()) > {0, 1, 2, maxent.SLOTS - 1}
    model = random_model(vocabulary)
    words = head + list(tails)
    numbers = vocabulary.numbers(words)
    for a, b in ((3, 5), (0, 0), (50, 7)):
        p = model.scores(numbers, np.full(len(words), a), np.full(len(words), b)) + np.array([0.0] * len(head) + [math.log10(c + 1) for c in tails.values()])
        # What is left is the place of unseen words in each class.
        unseen = 0.0
        for k in range(maxent.OWN, maxent.CLASSES):
            last = len(head) + k * maxent.TAIL_SLOTS
            unseen += 10 ** model.scores(np.array([last]), np.array([a]), np.array([b]))[0]
        assert abs((10**p).sum() + unseen - 1) < 1e-3


def plain_score(model, counts, text):
    """Token by token, with plain sums: the class's softmax, the slot's softmax in it, and the share of the slot."""
    v = model.vocabulary
    words = [*blank_words(text), maxent.END]
    total, before, before_that = 0.0, v.end, v.end
    for w in words:
        n = int(v.numbers([w])[0])
        h = model.histories
        k = int(v.classes[n])
        z = v.bias.astype(float) + np.clip(sum(model.weights[int(r[0])].astype(float) for r in h.rows(np.array([before]), np.array([before_that]))), -60, 60)
        p = math.exp(z[k]) / sum(map(math.exp, z))
        if k >= maxent.OWN:
            rows = h.inner_rows(np.array([before]), np.array([before_that]), np.array([k]))
            z = v.inner_bias[k].astype(float) + np.clip(sum(model.inner[int(r[0])].astype(float) for r in rows), -60, 60)
            slot = int(v.slots[n])
            p *= math.exp(z[slot]) / sum(map(math.exp, z))
            if slot == maxent.SLOTS - 1:
                members = [(x, c) for x, c in counts.items() if int(v.classes[v.numbers([x])[0]]) == k and int(v.slots[v.numbers([x])[0]]) == slot]
                p *= (counts.get(w, 0) + 1) / (sum(c for _, c in members) + len(members) + 1)
        total += math.log10(p)
        before, before_that = n, before
    return total


def test_scores_are_those_of_a_plain_version_alone_and_in_company(spark):
    vocabulary, head, tails = small_vocabulary()
    counts = dict(zip(head, vocabulary.counts.astype(int).tolist(), strict=True)) | tails
    model = random_model(vocabulary, 4)
    rng = random.Random(2)
    pool = [w.decode() for w in head[1:]] + [w.decode() for w in tails] + ["unseen", "never"]
    rows = [(i, " ".join(rng.choice(pool) for _ in range(rng.randrange(0, 12)))) for i in range(40)] + [(90, None), (91, ""), (92, rng.choice(pool))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    table = spark.createDataFrame([(bytearray(w), int(c)) for w, c in counts.items()], "word binary, c long")
    whole = {r.doc_id: r.score for r in maxent.score(maxent.numbered(docs.coalesce(1), vocabulary), model, table).collect()}
    for i, text in rows:
        assert math.isclose(whole[i], plain_score(model, counts, text), rel_tol=1e-5, abs_tol=1e-4), i
    spread = {r.doc_id: r.score for r in maxent.score(maxent.numbered(docs.repartition(11), vocabulary), model, table).collect()}
    assert all(abs(spread[i] - whole[i]) < 1e-6 for i in whole)
    for i in (0, 7, 92):
        alone = maxent.score(maxent.numbered(docs.where(f"doc_id = {i}"), vocabulary), model, table).first().score
        assert abs(alone - whole[i]) < 1e-6


def test_equal_texts_score_alike_and_frequent_words_fill_the_head(spark, monkeypatch):
    rows = [(i, f"alpha beta {'gamma' if i % 2 else 'delta'}") for i in range(20)]
    got = maxent.digest(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    for rest in (0, 1):
        scores = [r.score for r in got if r.doc_id % 2 == rest]
        assert max(scores) - min(scores) < 1e-6
    # A step of frequency that is larger than the head: its first words and the end token are kept.
    monkeypatch.setattr(maxent, "HEAD", 4)
    flat = spark.createDataFrame([(bytearray(f"w{k}".encode()), 5) for k in range(30)] + [(bytearray(maxent.END), 5)], "word binary, c long")
    head = maxent._head(flat)
    assert 4 <= len(head) <= 5 and maxent.END in dict(head)


def test_frequent_words_and_endings_have_classes_of_their_own():
    head = [(maxent.END, 90), *((f"w{k}aa".encode(), 80 - k) for k in range(40))]
    endings = [(b"aa", sum(c for _, c in head[1:]), 40), (maxent.END, 90, 1), *((bytes([97 + k // 26, 97 + k % 26]), 5, 5) for k in range(1, 60))]
    v = maxent.Vocabulary(head, endings, sum(c for _, c, _ in endings), 336)
    own = maxent.OWN
    assert len(set(v.classes[:own].tolist())) == own and (v.inside[:own] == 0).all()
    assert len(v.class_of_ending) == maxent.CLASSES - own - 1


def test_sums_by_key():
    rng = np.random.default_rng(6)
    for n, keys in ((1, 5), (700, 30), (700, 2000), (50, 1)):
        key, values = rng.integers(0, keys, n).astype(np.uint16), rng.normal(size=(n, 7)).astype(np.float32)
        sums, found, times = maxent.summed_by(values, key)
        assert found.tolist() == sorted(set(key.tolist())) and times.sum() == n
        for k, got, m in zip(found, sums, times, strict=True):
            assert m == (key == k).sum() and np.allclose(got, values[key == k].sum(0), atol=1e-4)


def test_words_split_and_counted_at_once_are_those_of_each_text(spark):
    odd = [None, "", "  \n\t ", " Lead\x0band\x0ctail\x1c \x85x\xa0y ", "ÀÉ İI ß 日本語　😀", "a\x00b\r\nC", "x" * 3000, "one"]
    words, sizes = maxent.split(pa.array(odd, pa.string()))
    want = [blank_words(t) for t in odd]
    assert words.to_pylist() == [w for ws in want for w in ws] and sizes.tolist() == list(map(len, want))
    batch = pa.RecordBatch.from_arrays([pa.array(odd), pa.array(range(len(odd)))], ["text", "n"])
    for size in (1, 10, 100, 1 << 20):
        cut = list(maxent.lots([batch, batch.slice(0, 0), batch], size))
        assert [n for some in cut for n in some.column("n").to_pylist()] == [*range(len(odd))] * 2 and all(some.num_rows for some in cut)
    docs = spark.createDataFrame([(t,) for t in odd], "text string")
    got = {bytes(r.word): r.c for r in maxent.count_words(docs.repartition(3)).collect()}
    assert got == Counter(w for ws in want for w in [*ws, maxent.END])


def test_texts_are_numbered_with_their_ends_and_rare_words(spark):
    vocabulary, head, tails = small_vocabulary()
    rare = [w.decode() for w in tails]
    texts = [None, f"{rare[0]} {rare[1]} {rare[0]}", "", f"w3on new {rare[2]} w4un New", "w1en"]
    for v, ends in ((vocabulary, 0), (maxent.Vocabulary([], [], 0, 0), 1)):
        got = {r.doc_id: r for r in maxent.numbered(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1), v).collect()}
        assert len({r.row for r in got.values()}) == len(texts)
        for i, t in enumerate(texts):
            words = [*blank_words(t), maxent.END]
            assert np.frombuffer(got[i].ids, "<i4").tolist() == [int(v.numbers([w])[0]) for w in words]
            assert dict(zip(map(bytes, got[i].rare), got[i].times, strict=True)) == Counter(w for w in words if w not in v.words)
        assert (maxent.END in map(bytes, got[0].rare)) == bool(ends)


def test_products_of_powers_score_like_sums_and_large_weights_take_the_sums():
    vocabulary, head, tails = small_vocabulary()
    numbers = vocabulary.numbers(head + list(tails))
    before, before_that = np.roll(numbers, 1), np.roll(numbers, 2)
    model = random_model(vocabulary, 8)
    assert all(x is not None for x in model.powers)
    plain = random_model(vocabulary, 8)
    plain._powers = [None, None]
    assert np.allclose(model.scores(numbers, before, before_that), plain.scores(numbers, before, before_that), atol=1e-5)
    large = random_model(vocabulary, 8)
    large.weights *= 30
    large.inner *= 30
    assert large.powers == [None, None] and np.isfinite(large.scores(numbers, before, before_that)).all()
    # A learner's step is that of one gradient for all features of a token, whichever rows it meets how often.
    learner, n = maxent.Learner(maxent.Model(vocabulary)), len(numbers)
    learner.step(numbers, before, before_that)
    rows = learner.model.histories.rows(before, before_that)
    assert learner.met[0].sum() == 3 * n and learner.met[0].tolist() == np.bincount(np.concatenate(rows), minlength=maxent.ROWS).tolist()
