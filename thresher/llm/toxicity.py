"""Toxicity by the nearest labelled examples under exact TF-IDF cosine.

Vectors are over all words of the labelled sample (``SAMPLE`` texts, least hash of their id first), and over word
beginnings that go with the label beyond chance: the first four to six characters, and the first five where two
words of a text share them. Document frequencies are counted over all documents. A term that goes
with the label weighs ``1 / PLAIN`` times as much as a plain one of the same frequency, so toxic texts are near toxic
examples, and clean texts near clean ones by their other words. A text is one example, with its rows and toxic rows.

The index keeps for each term its examples and weights, cut into blocks of 64 examples with the
largest weight of each block; examples near one pivot are neighbours, which keeps blocks alike. A query
sums the block maxima of its terms, which bounds every cosine in a block, scores blocks from the
best bound on, and stops where none can reach the k-th best. What the commonest terms add is a matrix product for
some queries at a time, and part of every bound. The k nearest vote with the square of their
cosine, against a small weight of the sample's share of toxic rows; nearest examples are the evidence.

The index is broadcast: at most ``SAMPLE`` texts of the sample, whatever the number of documents.

Defined cases: null and empty texts, and texts of unknown words alone, get the sample's share of toxic rows; rows without a
label or id are not learnt from; an id with several labels is toxic if one of them says so; equal texts with different labels
are one example with both; without training rows the score is 0; repeated rows get equal
scores; very long texts are read whole; further columns are kept, one that is named like a result as ``document_<name>``.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import DoubleType, StringType, StructField, StructType

from .common import SharedTable, batched, is_trained_on, parts, plain_words, prepare, rows_of
from .decontaminate import _arrow

#: Bound of the labelled rows that the classifier is fitted on.
SAMPLE = 4_000
TERMS, K, BLOCK = 512, 15, 64
#: Weight of a plain term beside one that goes with the label, of the share of all rows among the votes, and pivots.
PLAIN, SHARE_WEIGHT, PIVOTS = 0.1, 0.05, 64
#: Terms of more than one in so many examples are kept as a matrix.
COMMON = 20
RESULTS = ("score", "predicted", "evidence")
DIVISOR, HELD_OUT = 5, 0
PREFIXES = (4, 5, 6)
_FLUSH = 400_000


def word_terms(word: bytes) -> list[bytes]:
    """A word and its prefixes, as marked terms."""
    text = word.decode("utf-8", "surrogatepass")
    return [b"=" + word, *(b"^" + text[:n].encode("utf-8", "surrogatepass") for n in PREFIXES if len(text) >= n)]


def doc_terms(words: list[bytes]) -> Counter:
    """How often each term occurs; ``2`` marks a prefix that two different words share."""
    found: Counter = Counter()
    for word, n in Counter(words).items():
        for t in word_terms(word):
            found[t] += n
    twice = Counter(w.decode("utf-8", "surrogatepass")[:5] for w in set(words) if len(w) >= 5)
    for prefix, n in twice.items():
        if n > 1 and len(prefix) == 5:
            found[b"2" + prefix.encode("utf-8", "surrogatepass")] = n
    return found


def training_rows(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id (the smallest), text, n and toxic (rows, toxic rows) of the texts of the sampled ids."""
    usable = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & is_trained_on(F.col("doc_id"), DIVISOR, HELD_OUT))
    by_id = usable.groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    h = F.xxhash64("doc_id")
    # Twice the sample is expected below this hash, so the last sort sees few rows of any number.
    below = int(min(1.0, 2 * sample / max(1, by_id.count())) * (1 << 64)) - (1 << 63)
    near = by_id.where(h < below) if below < (1 << 63) - 1 else by_id
    some = near.orderBy(h, "doc_id").limit(sample)
    # Bounded by ``sample`` rows of an id and a label.
    met = docs.select("doc_id", "text").join(F.broadcast(some), "doc_id")
    return met.groupBy("text").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("n"), F.sum("toxic").alias("toxic"))


def association(toxic_with: int, clean_with: int, toxic: int, clean: int) -> float:
    """The likelihood ratio statistic of a term and the label; negative if it goes with clean texts."""
    n, total = toxic_with + clean_with, 0.0
    for a, b, m in ((toxic_with, clean_with, n), (toxic - toxic_with, clean - clean_with, toxic + clean - n)):
        for x, of in ((a, toxic), (b, clean)):
            if x:
                total += 2 * x * math.log(x * (toxic + clean) / (m * of))
    return total if toxic_with * clean > clean_with * toxic else -total


def choose_terms(rows: DataFrame, terms: int = TERMS, least: int = 3) -> list[bytes]:
    """The terms that go with toxic rows most clearly, beyond what so many candidates show by chance."""
    schema = pa.schema([("term", pa.binary()), ("toxic_with", pa.int64()), ("clean_with", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out() -> Iterator[tuple]:
            with_: tuple[Counter, Counter] = (Counter(), Counter())
            for text, n, toxic in rows_of(batches, "text", "n", "toxic"):
                with_[2 * toxic > n].update(doc_terms(plain_words(text)).keys())
                if len(with_[0]) + len(with_[1]) > _FLUSH:
                    yield from _pairs(*with_)
                    with_ = (Counter(), Counter())
            yield from _pairs(*with_)

        return batched(out(), schema, 8192)

    is_toxic = 2 * F.col("toxic") > F.col("n")
    totals = rows.agg(F.count_if(is_toxic), F.count_if(~is_toxic)).first()
    toxic, clean = (int(x or 0) for x in totals)
    if not toxic or not clean:
        return []
    counts = rows.mapInArrow(run, "term binary, toxic_with long, clean_with long").groupBy("term").agg(F.sum("toxic_with").alias("a"), F.sum("clean_with").alias("b"))
    counts = counts.where(F.col("a") >= least)
    # A lower bound of the statistic's interest; the rest is decided on the few that are left.
    likely = counts.where(F.col("a") * clean > 2 * F.col("b") * toxic).orderBy(F.desc(F.col("a") / (F.col("a") + F.col("b") + 1) * F.log1p("a")), "term").limit(16 * terms).collect()
    scored = sorted(((association(x.a, x.b, toxic, clean), bytes(x.term)) for x in likely), key=lambda s: (-s[0], s[1]))
    return [t for s, t in scored[:terms] if s >= 16.0]


def _pairs(clean: Counter, toxic: Counter) -> Iterator[tuple]:
    for t, n in toxic.items():
        yield t, n, clean.get(t, 0)
    for t, n in clean.items():
        if t not in toxic:
            yield t, 0, n


def sample_words(rows: DataFrame) -> list[bytes]:
    """The distinct words of the sample, sorted."""
    schema = pa.schema([("word", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: set[bytes] = set()
        for (text,) in rows_of(batches, "text"):
            found.update(plain_words(text))
        return batched(((w,) for w in found), schema, 16384)

    # Words of at most ``SAMPLE`` texts.
    return sorted(rows.select("text").mapInArrow(run, "word binary").distinct().toArrow().column("word").to_pylist())


class TermFinder:
    """Word to its number, -1 for unknown ones; every word is looked at once.

    Terms are numbered: words first, then the word beginnings that were chosen. ``more`` has the words that
    begin so, with the numbers of these terms (``2`` terms as -1 - number).
    """

    def __init__(self, words: list[bytes], chosen: list[bytes], room: int = 100_000):
        self.seen: dict[bytes, int] = {}
        self.words = {w: k for k, w in enumerate(words)}
        self.begin = {t[1:]: len(words) + k for k, t in enumerate(chosen) if t[:1] == b"^"}
        self.twice = {t[1:]: len(words) + k for k, t in enumerate(chosen) if t[:1] == b"2"}
        self.more: dict[bytes, tuple[int, ...]] = {}
        self.room = room

    def look(self, word: bytes) -> int:
        text = word.decode("utf-8", "surrogatepass")
        more = ()
        for n in PREFIXES:
            if len(text) >= n and (t := self.begin.get(text[:n].encode("utf-8", "surrogatepass"))) is not None:
                more += (t,)
        if len(text) >= 5 and (t := self.twice.get(text[:5].encode("utf-8", "surrogatepass"))) is not None:
            more += (-1 - t,)
        if more:
            self.more[word] = more
        self.seen[word] = found = self.words.get(word, -1)
        return found

    def of(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Terms of a text, ascending, and how often each occurs; ``2`` terms count if two different words share them."""
        if len(self.seen) >= self.room:
            self.seen.clear()
            self.more.clear()
        words = plain_words(text)
        numbers = np.fromiter(map(self.seen.get, words, repeat(-2)), np.int64, len(words))
        for k in np.flatnonzero(numbers == -2).tolist():
            numbers[k] = self.look(words[k])
        terms, times = np.unique(numbers, return_counts=True)
        if len(terms) and terms[0] < 0:
            terms, times = terms[1:], times[1:]
        hits = [w for w in words if w in self.more]
        if not hits:
            return terms, times
        found: Counter = Counter()
        shared: Counter = Counter()
        for w, n in Counter(hits).items():
            for k in self.more[w]:
                if k >= 0:
                    found[k] += n
                else:
                    shared[-1 - k] += 1
        found.update({k: n for k, n in shared.items() if n > 1})
        # Their numbers lie behind those of the words.
        own = sorted(found)
        return np.concatenate((terms, np.array(own, np.int64))), np.concatenate((times, np.array([found[k] for k in own], np.int64)))


def _ranges(low: np.ndarray, high: np.ndarray) -> np.ndarray:
    """All numbers of the ranges [low, high), one range after the other."""
    size = high - low
    return np.arange(size.sum()) + np.repeat(low - np.cumsum(size) + size, size)


class BlockMaxIndex:
    """Examples by term, in blocks with their largest weight; cosines are exact."""

    def __init__(self, weight: np.ndarray, examples: list[tuple[np.ndarray, np.ndarray, int, int, object]]):
        """weight: of each term, its idf and what its label association adds; examples: (terms, times, rows, toxic rows, an id)."""
        self.weight = weight
        rows, toxic = sum(x[2] for x in examples), sum(x[3] for x in examples)
        self.share = toxic / rows if rows else 0.0
        # Bytes with the highest one first sort like the term numbers themselves.
        examples = sorted((x for x in examples if len(x[0])), key=lambda x: (x[0].astype(">u4").tobytes(), str(x[4])))
        if len(examples) > BLOCK:
            # Every 1 / PIVOTS-th example is a pivot; the nearest one says with whom an example lies in a block.
            pivots = BlockMaxIndex(weight, [])
            pivots._build(examples[:: -(-len(examples) // PIVOTS)])
            home = [best[0][1] if (best := pivots.nearest(*x[:2], k=1)) else -1 for x in examples]
            examples = [examples[i] for i in np.argsort(home, kind="stable").tolist()]
            del pivots
        self._build(examples)

    def _build(self, examples: list[tuple]) -> None:
        self.n, self.blocks = len(examples), -(-len(examples) // BLOCK)
        self.names = [x[4] for x in examples]
        self.rows, self.toxic = np.array([x[2] for x in examples], float), np.array([x[3] for x in examples], float)
        vectors = [self.vector(x[0], x[1]) for x in examples]
        terms = np.concatenate([t for t, _ in vectors]) if vectors else np.empty(0, np.int64)
        weights = np.concatenate([w for _, w in vectors]) if vectors else np.empty(0)
        who = np.repeat(np.arange(len(vectors)), [len(t) for t, _ in vectors]) if vectors else np.empty(0, np.int64)
        # Terms of many examples are rows of a matrix, the others lists of postings.
        often = np.flatnonzero(np.bincount(terms, minlength=len(self.weight)) * COMMON > max(self.n, COMMON * BLOCK))
        self.common_at = np.full(len(self.weight) + 1, -1)
        self.common_at[often] = np.arange(len(often))
        self.common = np.zeros((len(often), self.blocks * BLOCK))
        at = self.common_at.take(terms)
        self.common[at[at >= 0], who[at >= 0]] = weights[at >= 0]
        terms, who, weights = terms[at < 0], who[at < 0], weights[at < 0]
        order = np.lexsort((who, terms))
        terms, self.who, self.posting = terms[order], who[order].astype(np.int32), weights[order]
        # A piece is a term's postings in one block.
        block = self.who // BLOCK
        new = np.flatnonzero(np.concatenate(([True], (terms[1:] != terms[:-1]) | (block[1:] != block[:-1])))) if len(terms) else np.empty(0, np.int64)
        self.piece_block, self.piece_at = block[new], np.append(new, len(terms))
        self.piece_max = np.maximum.reduceat(self.posting, new) if len(new) else np.empty(0)
        self.term_at = np.searchsorted(terms[new], np.arange(len(self.weight) + 1))

    def vector(self, terms: np.ndarray, times: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Terms and weights of length 1."""
        raw = (1 + np.log(times)) * self.weight.take(terms)
        norm = math.sqrt(float(raw @ raw)) if len(raw) else 0.0
        return (terms, raw / norm) if norm else (terms[:0], raw[:0])

    def nearest(self, terms: np.ndarray, times: np.ndarray, k: int = K) -> list[tuple[float, int]]:
        """(cosine, example) of the k nearest, larger cosines and then smaller numbers first."""
        return self.nearest_of_all([(terms, times)], k)[0]

    def nearest_of_all(self, texts: list[tuple[np.ndarray, np.ndarray]], k: int = K) -> list[list[tuple[float, int]]]:
        """The same of some texts: the common terms of all of them are one matrix product."""
        vectors = [self.vector(*x) for x in texts]
        query = np.zeros((len(vectors), len(self.common)))
        for row, (terms, weights) in zip(query, vectors, strict=True):
            at = self.common_at.take(terms)
            row[at[at >= 0]] = weights[at >= 0]
        begun = query @ self.common
        return [self._best(start, *x, k) for start, x in zip(begun, vectors, strict=True)]

    def _best(self, begun: np.ndarray, terms: np.ndarray, query: np.ndarray, k: int) -> list[tuple[float, int]]:
        """Best blocks first. ``begun`` holds what the common terms add to every example."""
        low, high = self.term_at.take(terms), self.term_at.take(terms + 1)
        pieces, of_piece = _ranges(low, high), np.repeat(query, high - low)
        block = self.piece_block.take(pieces)
        begun = begun.reshape(self.blocks, BLOCK)
        bound = np.bincount(block, of_piece * self.piece_max.take(pieces), minlength=self.blocks) + begun.max(1, initial=0.0)
        order = np.argsort(-bound, kind="stable")
        scores, names = np.empty(0), np.empty(0, np.int64)
        at, step, worst = 0, 16, 0.0
        while at < len(order) and bound[order[at]] > 0 and bound[order[at]] >= worst - 1e-12:
            chosen = order[at : at + step]
            chosen = chosen[bound.take(chosen) >= worst - 1e-12]
            place = np.full(self.blocks, -1)
            place[chosen] = np.arange(len(chosen))
            where = place.take(block)
            mine = np.flatnonzero(where >= 0)
            own = pieces.take(mine)
            first, last = self.piece_at.take(own), self.piece_at.take(own + 1)
            postings = _ranges(first, last)
            to = np.repeat(where.take(mine) * BLOCK, last - first) + self.who.take(postings) % BLOCK
            more = np.bincount(to, self.posting.take(postings) * np.repeat(of_piece.take(mine), last - first), minlength=len(chosen) * BLOCK)
            scores = np.concatenate((scores, begun[chosen].ravel() + more))
            names = np.concatenate((names, (chosen[:, None] * BLOCK + np.arange(BLOCK)).ravel()))
            if len(scores) > k:
                worst = max(0.0, float(np.partition(scores, len(scores) - k)[len(scores) - k]))
                kept = scores >= worst - 1e-12
                scores, names = scores[kept], names[kept]
            at, step = at + len(chosen), 2 * step
        hits = np.flatnonzero(scores > 1e-15)
        return sorted(zip(scores[hits].tolist(), names[hits].tolist(), strict=True), key=lambda x: (-round(x[0], 12), x[1]))[:k]

    def votes(self, best: list[tuple[float, int]]) -> tuple[float, str]:
        """The share of toxic votes, and the ids of the nearest examples with their cosines."""
        if not best:
            return self.share, ""
        votes = np.array([c * c for c, _ in best])
        who = np.array([n for _, n in best], int)
        share = (float((votes * self.toxic[who] / self.rows[who]).sum()) + self.share * SHARE_WEIGHT) / (float(votes.sum()) + SHARE_WEIGHT)
        return min(1.0, share), ",".join(f"{self.names[n]}:{c:.3f}" for c, n in best[:3])

    def scores(self, texts: list[tuple[np.ndarray, np.ndarray]], lot: int = 64) -> Iterator[tuple[float, str]]:
        """Score and evidence of each text."""
        for low in range(0, len(texts), lot):
            yield from map(self.votes, self.nearest_of_all(texts[low : low + lot]))


class Scorer:
    """What is broadcast: the terms and the index."""

    def __init__(self, words: list[bytes], chosen: list[bytes], index: BlockMaxIndex):
        self.words, self.chosen, self.index = words, chosen, index

    def finder(self) -> TermFinder:
        return TermFinder(self.words, self.chosen)


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, terms: int = TERMS) -> Scorer:
    """The index of the sample, with document frequencies over all of ``docs``."""
    spark = docs.sparkSession
    prepare(spark)
    rows = SharedTable(training_rows(docs, labels, sample), "toxicity-sample").read()
    with_label = choose_terms(rows, terms)
    words = sample_words(rows)
    chosen = [t for t in with_label if t[:1] != b"="]
    held = spark.sparkContext.broadcast((words, chosen))
    size = len(words) + len(chosen)
    counted = pa.schema([("term", pa.int32()), ("n", pa.int64())])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder, found, rows_seen = TermFinder(*held.value), np.zeros(size, np.int64), 0
        for (text,) in rows_of(batches, "text"):
            found[finder.of(text)[0]] += 1
            rows_seen += 1
        met = np.flatnonzero(found)
        if rows_seen:
            yield pa.RecordBatch.from_arrays([pa.array(np.append(met, -1), pa.int32()), pa.array(np.append(found[met], rows_seen), pa.int64())], schema=counted)

    # A row for each term of the sample: bounded by its texts.
    found = docs.select("text").mapInArrow(count, "term int, n long").groupBy("term").agg(F.sum("n").alias("n")).toArrow()
    number, df = found.column("term").to_numpy(), found.column("n").to_numpy()
    frequency = np.zeros(size)
    frequency[number[number >= 0]] = df[number >= 0]
    n_docs = int(df[number < 0].sum())
    plain = np.full(size, PLAIN)
    plain[len(words) :] = 1.0
    place = {w: k for k, w in enumerate(words)}
    plain[[place[t[1:]] for t in with_label if t[:1] == b"=" and t[1:] in place]] = 1.0
    weight = (np.log((1 + n_docs) / (1 + frequency)) + 1) * plain
    vectors = pa.schema([("terms", pa.binary()), ("times", pa.binary()), ("n", pa.int64()), ("toxic", pa.int64()), ("doc_id", _arrow(docs.schema["doc_id"].dataType))])

    def vectorise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder = TermFinder(*held.value)

        def out() -> Iterator[tuple]:
            for text, n, toxic, doc_id in rows_of(batches, "text", "n", "toxic", "doc_id"):
                terms, times = finder.of(text)
                yield terms.astype("<i4").tobytes(), times.astype("<i4").tobytes(), n, toxic, doc_id

        return batched(out(), vectors)

    kind = docs.schema["doc_id"].dataType.simpleString()
    # At most ``SAMPLE`` examples.
    collected = rows.mapInArrow(vectorise, f"terms binary, times binary, n long, toxic long, doc_id {kind}").toArrow().to_pylist()
    examples = [(np.frombuffer(x["terms"], "<i4").astype(np.int64), np.frombuffer(x["times"], "<i4").astype(np.int64), x["n"], x["toxic"], x["doc_id"]) for x in collected]
    return Scorer(words, chosen, BlockMaxIndex(weight, examples))


def score(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """All columns of the documents, with ``score``, ``predicted`` and ``evidence`` behind them."""
    held = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, sample))
    taken = {f"document_{c}" if c in RESULTS else c: c for c in docs.columns}
    renamed = docs.select(*[F.col(f"`{old}`").alias(new) for new, old in taken.items()])
    plain = StructType([*renamed.schema.fields, StructField("score", DoubleType()), StructField("evidence", StringType())])
    schema = to_arrow_schema(plain)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder, index = held.value.finder(), held.value.index
        for batch in parts(batches):
            found = list(index.scores([finder.of(t) for t in batch.column("text").to_pylist()]))
            columns = [batch.column(k).cast(schema.field(k).type) for k in range(batch.num_columns)]
            yield pa.RecordBatch.from_arrays([*columns, pa.array([s for s, _ in found], pa.float64()), pa.array([e for _, e in found], pa.string())], schema=schema)

    return renamed.mapInArrow(run, plain).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def keep_clean(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """The documents whose score is below 0.5, with all their columns whatever their names."""
    held = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, sample))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finder, index = held.value.finder(), held.value.index
        for batch in parts(batches):
            scored = index.scores([finder.of(t) for t in batch.column("text").to_pylist()])
            yield batch.filter(pa.array([x < 0.5 for x, _ in scored], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def digest(docs: DataFrame, labels: DataFrame) -> DataFrame:
    held_out = ~is_trained_on(F.col("doc_id"), DIVISOR, HELD_OUT)
    return score(docs.select("doc_id", "text"), labels).select("doc_id", held_out.alias("held_out"), "score", "predicted", "evidence")
