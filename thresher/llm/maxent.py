"""A hashed maximum-entropy language model with a class-factored softmax.

P(word | history) = P(class | history) P(word | class, history). The class comes from a softmax over
hashed features of the history: the last word, the one before it (a skip feature) and both
together, each a row of one weight table. Inside a class a second softmax, over hashed features of the
class with the last word and with the one before it, chooses one of the class's most frequent words or
the slot of all its others; these share their slot by add-one counts, with one place for words never
seen. The probabilities of all words add up to one.

Classes: the most frequent words are classes of their own, every other word has the class of its
last two bytes before closing punctuation; rare endings share a class. A word's class needs no
count, so words outside the ``HEAD`` most frequent have one too.

Everything is learnt from all training rows. Counts are summed per partition and then by word. Texts
are turned into numbers once and stored; training and scoring read these. Weights come from
distributed gradient updates: every learner (a task of about ``LEARNER_TOKENS`` tokens) takes AdaGrad
steps over its rows in numpy batches and hands on the rows it has touched, and rows are averaged by
how often each learner met them. Model, head words and class sums have a fixed size and are broadcast;
the counts of all other words stay a table, which grows with the corpus, and scoring joins it with the
rarer words of each document.

A history begins anew with every text, so a text's score depends on the model and the text alone.

Defined cases: a null or empty text is the end token alone; without training rows the counts are
zero and every word is unknown; repeated rows are scored each; null ids are trained on by the
remainder of the empty string; a very long text is one batch of numbers; further columns are ignored.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterable, Iterator
from itertools import pairwise

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SharedTable, batched, is_trained_on, prepare, rows_of
from .decontaminate import _arrow

DIVISOR, HELD_OUT = 7, 2
#: No word holds white space, so this is no word.
END = b"\n"
HEAD, OWN, CLASSES = 1 << 18, 24, 64
#: Places of a class's second softmax; the last one is for all words without a place of their own.
SLOTS = 32
#: Rows of the two weight tables. A row number has 16 bits at most, which sorts fast.
ROWS, INNER_ROWS, TAIL_SLOTS = 1 << 15, 1 << 16, 1 << 10
LEARNER_TOKENS = 8_000_000
BATCH, STEP, RATE = 4096, 1024, 0.2
ROW_BLOCK = 256
#: Keys with many rows that are summed by one product.
MANY = 24
LIMIT = 60.0
#: Bytes of text that are split at once, and bytes of words that are counted at once.
TEXT_BYTES, COUNT_BYTES = 8 << 20, 16 << 20
_PUNCTUATION = b".,;:!?|"


def lots(batches: Iterable[pa.RecordBatch], size: int = TEXT_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches in slices that end at the row with which ``size`` bytes of text are full."""
    for batch in batches:
        full = np.cumsum(pc.fill_null(pc.binary_length(batch.column("text")), 0).to_numpy(zero_copy_only=False).astype(np.int64)) // size
        cuts = [0, *(np.flatnonzero(np.diff(full, prepend=0)) + 1).tolist(), batch.num_rows]
        for low, high in pairwise(cuts):
            if low < high:
                yield batch.slice(low, high - low)


def split(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """The words of all texts, one text after another, and each text's number of words; they are those of ``blank_words``."""
    lists = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
    words, sizes = lists.flatten(), pc.list_value_length(lists).to_numpy().astype(np.int64)
    # White space at either end of a text leaves an empty word there.
    nothing = pc.binary_length(words).to_numpy() == 0
    if nothing.any():
        sizes -= np.bincount(np.repeat(np.arange(len(sizes)), sizes)[nothing], minlength=len(sizes))
        words = words.filter(pa.array(~nothing))
    return words.cast(pa.binary()), sizes


def count_words(docs: DataFrame) -> DataFrame:
    """(word, c) over all rows; every text adds one end token."""
    prepare(docs.sparkSession)
    schema = pa.schema([("word", pa.binary()), ("c", pa.int64())])

    def counted(held: list[pa.Array]) -> Iterator[pa.RecordBatch]:
        words, c = pa.chunked_array(held).value_counts().flatten()
        found = pa.RecordBatch.from_arrays([words, c], schema=schema)
        for low in range(0, found.num_rows, 16384):
            yield found.slice(low, 16384)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Array] = []
        weight = ends = 0
        for some in lots(batches):
            words, _ = split(some.column("text"))
            ends += some.num_rows
            held.append(words)
            weight += words.nbytes
            if weight > COUNT_BYTES:
                yield from counted(held)
                held, weight = [], 0
        if held:
            yield from counted(held)
        if ends:
            yield pa.RecordBatch.from_arrays([pa.array([END], pa.binary()), pa.array([ends])], schema=schema)

    return docs.select("text").mapInArrow(run, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))


def ending(word: bytes) -> bytes:
    return (word.rstrip(_PUNCTUATION) or word)[-2:]


class Vocabulary:
    """Head words with counts, classes with their sums, and the number of each word."""

    def __init__(self, head: list[tuple[bytes, int]], endings: list[tuple[bytes, int, int]], total: int, distinct: int):
        """head: most frequent words first; endings: (ending, sum of counts, words), all of them together hold all words."""
        self.words, self.counts = [w for w, _ in head], np.array([c for _, c in head], float)
        self.total, self.distinct = total, distinct
        own = self.words[:OWN]
        self.class_of_ending = {e: OWN + k for k, (e, _, _) in enumerate(endings[: CLASSES - OWN - 1])}
        sums, kinds = np.zeros(CLASSES), np.zeros(CLASSES)
        for e, c, n in endings:
            k = self.class_of_ending.get(e, CLASSES - 1)
            sums[k] += c
            kinds[k] += n
        for k, w in enumerate(own):
            shared = self.class_of_ending.get(ending(w), CLASSES - 1)
            sums[shared] -= self.counts[k]
            kinds[shared] -= 1
            sums[k] = self.counts[k]
        self.bias = np.log((sums + 1) / (sums.sum() + CLASSES)).astype(np.float32)
        self.bias[len(own) : OWN] = -60.0
        classes = np.array([k if k < len(own) else self.class_of_ending.get(ending(w), CLASSES - 1) for k, w in enumerate(self.words)], np.int64)
        # The most frequent words of a class have a slot; the rest of its count and words is the last one's.
        slots = np.full(len(classes), SLOTS - 1, np.int64)
        inner = np.full((CLASSES, SLOTS), -np.inf)
        order = np.flatnonzero(classes >= len(own)) if len(classes) else np.empty(0, np.int64)
        order = order[np.argsort(classes[order], kind="stable")]
        place = np.arange(len(order)) - np.searchsorted(classes[order], classes[order])
        chosen, place = order[place < SLOTS - 1], place[place < SLOTS - 1]
        slots[chosen] = place
        inner[classes[chosen], place] = np.log(self.counts[chosen] + 1)
        np.subtract.at(sums, classes[chosen], self.counts[chosen])
        np.subtract.at(kinds, classes[chosen], 1)
        rest = np.maximum(sums + kinds + 1, 1.0)
        inner[:, SLOTS - 1] = np.log(rest)
        inner -= np.log(np.exp(inner).sum(1, keepdims=True))
        self.inner_bias = np.maximum(inner, -60.0).astype(np.float32)
        log_rest = np.log10(rest)
        tails = np.repeat(np.arange(CLASSES), TAIL_SLOTS)
        self.classes = np.concatenate([classes, tails]).astype(np.int64)
        self.slots = np.concatenate([slots, np.full(len(tails), SLOTS - 1)]).astype(np.int64)
        inside = np.where(slots < SLOTS - 1, 0.0, np.log10(self.counts + 1) - log_rest[classes]) if len(classes) else np.empty(0)
        inside[: len(own)] = 0.0
        #: Of a tail word, what its count adds comes from the join.
        self.inside = np.concatenate([inside, -log_rest[tails]])
        self.norm = math.log10(total + distinct + 1)
        self.base = np.log10(self.counts + 1) - self.norm
        self.end = self.words.index(END) if END in self.words else int(self._tails([END])[0])

    def _tails(self, words: list[bytes]) -> np.ndarray:
        own, shared = self.class_of_ending.get, CLASSES - 1
        classes = np.fromiter((own(ending(w), shared) for w in words), np.int64, len(words))
        return len(self.words) + classes * TAIL_SLOTS + np.fromiter(map(zlib.crc32, words), np.int64, len(words)) % TAIL_SLOTS

    def numbers(self, words: list[bytes]) -> np.ndarray:
        """Head words by frequency; the others by their class and a hash."""
        return self.numbers_of(pa.array(words, pa.binary()), pa.array(self.words, pa.binary()))[0]

    def numbers_of(self, words: pa.Array, head: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.DictionaryArray]:
        """The numbers of all words, the places of words outside the head, and these words. ``head`` is ``words`` of this, as an array."""
        found = pc.fill_null(pc.index_in(words, value_set=head), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        at = np.flatnonzero(found < 0)
        tails = words.take(pa.array(at)).dictionary_encode()
        found[at] = self._tails(tails.dictionary.to_pylist()).take(tails.indices.to_numpy())
        return found, at, tails


def vocabulary(counts: DataFrame) -> Vocabulary:
    """From the counts of all words: fixed-size head and class sums."""
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count("*")).first()
    head = _head(counts)
    schema = pa.schema([("e", pa.binary()), ("c", pa.int64()), ("n", pa.int64())])

    def by_ending(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[bytes, list[int]] = {}
        for word, c in rows_of(batches, "word", "c"):
            have = sums.setdefault(ending(word), [0, 0])
            have[0] += c
            have[1] += 1
        return batched(((e, c, n) for e, (c, n) in sums.items()), schema)

    by = counts.mapInArrow(by_ending, "e binary, c long, n long").groupBy("e").agg(F.sum("c").alias("c"), F.sum("n").alias("n"))
    # At most two bytes: 65,536 endings and the single bytes.
    endings = [(bytes(x.e), x.c, x.n) for x in by.orderBy(F.desc("c"), "e").collect()]
    return Vocabulary(head, endings, total, distinct)


def _head(counts: DataFrame) -> list[tuple[bytes, int]]:
    """The most frequent words down to a frequency, ``HEAD`` at most; steps of frequency are a sixteenth of a doubling.

    A histogram of a few hundred steps finds the frequency, so no task sorts more than the head.
    """
    step = F.floor(F.log2("c") * 16).cast("int")
    sizes = sorted(((r.step, r.n) for r in counts.groupBy(step.alias("step")).agg(F.count("*").alias("n")).collect()), reverse=True)
    lowest, total = None, 0
    for at, n in sizes:
        total += n
        if total > HEAD:
            break
        lowest = at
    if lowest is None:
        # More words of the highest frequency than the head holds: the first of them.
        chosen = counts.where(step == sizes[0][0]).orderBy(F.desc("c"), "word").limit(HEAD) if sizes else counts
    else:
        chosen = counts.where(step >= lowest)
    # The end token is met in every text, so it never is a rare word.
    found = chosen.select("word", "c").unionByName(counts.where(F.col("word") == F.lit(END)).select("word", "c")).distinct().toArrow()
    return sorted(zip(found.column("word").to_pylist(), found.column("c").to_pylist(), strict=True), key=lambda x: (-x[1], x[0]))


class Histories:
    """Weight rows of the histories of tokens."""

    def __init__(self, vocabulary: Vocabulary):
        n = np.arange(len(vocabulary.classes), dtype=np.uint64)
        mix = lambda k: (n + np.uint64(k)) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(20)
        mask = np.uint64(ROWS - 1)
        self.last, self.skip = (mix(1) & mask).astype(np.uint16), (mix(7919) & mask).astype(np.uint16)
        self.pair, self.inner_last, self.inner_skip = mix(104729), mix(31337) * np.uint64(0xD6E8FEB86659FD93), mix(65537) * np.uint64(0xA24BAED4963EE407)
        self.of_class = np.arange(CLASSES, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        self.vocabulary, self.mask = vocabulary, mask

    def rows(self, before: np.ndarray, before_that: np.ndarray) -> tuple[np.ndarray, ...]:
        """Of the class: last word, word before it, both."""
        both = (self.pair.take(before) * np.uint64(31) + self.pair.take(before_that) * np.uint64(0x2545F4914F6CDD1D) >> np.uint64(9)) & self.mask
        return self.last.take(before), self.skip.take(before_that), both.astype(np.uint16)

    def inner_rows(self, before: np.ndarray, before_that: np.ndarray, classes: np.ndarray) -> tuple[np.ndarray, ...]:
        """Of the word in its class: the class with each of the two words."""
        k, mask = self.of_class.take(classes), np.uint64(INNER_ROWS - 1)
        return tuple(((h.take(w) + k >> np.uint64(at)) & mask).astype(np.uint16) for h, w, at in ((self.inner_last, before, 17), (self.inner_skip, before_that, 19)))


def histories_of(numbers: np.ndarray, starts: np.ndarray, end: int) -> tuple[np.ndarray, np.ndarray]:
    """The last word and the one before it of every token; texts begin at ``starts``, behind nothing but ends."""
    before, before_that = np.empty_like(numbers), np.empty_like(numbers)
    before[1:], before_that[2:] = numbers[:-1], numbers[:-2]
    before[starts] = before_that[starts] = end
    second = starts[np.diff(np.append(starts, len(numbers))) > 1] + 1
    before_that[second] = end
    return before, before_that


def _softmax(weights: np.ndarray, rows: tuple[np.ndarray, ...], bias: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Exponentials of the scores and their sums; far inside what a 32-bit float holds. ``bias`` has a row for each token."""
    z = weights.take(rows[0], axis=0)
    for r in rows[1:]:
        z += weights.take(r, axis=0)
    if z.max(initial=0) > LIMIT or z.min(initial=0) < -LIMIT:
        np.clip(z, -LIMIT, LIMIT, out=z)
    z += bias
    # Biases are -60 at least and scores add LIMIT at most: sums are neither 0 nor infinite while one bias is near 0.
    np.exp(z, out=z)
    # A product with ones adds a row's few places several times as fast as a sum along them.
    return z, (z @ np.ones(z.shape[1], z.dtype))[:, None]


def _for_each(bias: np.ndarray, n: int) -> np.ndarray:
    """One bias for n tokens, written out: adding it is one pass instead of one for each token."""
    return np.tile(bias, (n, 1))


class Model:
    """Weight rows over the log frequencies of classes, and of words inside their class."""

    def __init__(self, vocabulary: Vocabulary, weights: np.ndarray | None = None, inner: np.ndarray | None = None):
        self.vocabulary = vocabulary
        self.weights = np.zeros((ROWS, CLASSES), np.float32) if weights is None else weights
        self.inner = np.zeros((INNER_ROWS, SLOTS), np.float32) if inner is None else inner
        self._histories: Histories | None = None
        self._powers: list[np.ndarray | None] | None = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_histories": None, "_powers": None}

    @property
    def histories(self) -> Histories:
        if self._histories is None:
            self._histories = Histories(self.vocabulary)
        return self._histories

    @property
    def powers(self) -> list[np.ndarray | None]:
        """Exponentials of both tables, of a table whose sums may pass ``LIMIT`` none. Scoring makes them once; it changes no weights."""
        if self._powers is None:
            self._powers = [np.exp(w) if np.abs(w).max() * n <= LIMIT else None for w, n in ((self.weights, 3), (self.inner, 2))]
        return self._powers

    def scores(self, numbers: np.ndarray, before: np.ndarray, before_that: np.ndarray) -> np.ndarray:
        """log10 probability of each token given its history; of a tail word without its count's part."""
        v, h = self.vocabulary, self.histories
        out = np.empty(len(numbers))
        bias, inner_powers = _for_each(v.bias, min(BATCH, len(numbers))), np.exp(v.inner_bias)
        bias_powers = np.exp(bias)
        for low in range(0, len(numbers), BATCH):
            n, b, bb = (x[low : low + BATCH] for x in (numbers, before, before_that))
            k = v.classes.take(n)
            log = _log_shares(self.weights, self.powers[0], h.rows(b, bb), bias[: len(k)], bias_powers[: len(k)], k)
            shared = np.flatnonzero(k >= OWN)
            if len(shared):
                k = k[shared]
                log[shared] += _log_shares(self.inner, self.powers[1], h.inner_rows(b[shared], bb[shared], k), v.inner_bias.take(k, axis=0), inner_powers.take(k, axis=0), v.slots.take(n[shared]))
            out[low : low + BATCH] = log
        return out / math.log(10) + v.inside.take(numbers)


def _log_shares(weights: np.ndarray, powers: np.ndarray | None, rows: tuple[np.ndarray, ...], bias: np.ndarray, bias_powers: np.ndarray, truth: np.ndarray) -> np.ndarray:
    """Logarithm of the softmax at each token's ``truth``. Where sums stay within ``LIMIT``, a product of the rows' exponentials spares one for each place."""
    each = np.arange(len(truth))
    if powers is None:
        z, total = _softmax(weights, rows, bias)
        return np.log(z[each, truth].astype(float)) - np.log(total[:, 0].astype(float))
    z = powers.take(rows[0], axis=0)
    for r in rows[1:]:
        z *= powers.take(r, axis=0)
    total = np.einsum("ij,ij->i", z, bias_powers)
    return np.log(z[each, truth].astype(float)) + bias[each, truth] - np.log(total.astype(float))


def summed_by(values: np.ndarray, key: np.ndarray, few: int = 3) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sums of the rows of each key, the keys and their numbers of rows. Several keys for each row follow one another, all rows' first ones first.

    Most keys have one row, which is taken as it is; a few rows are added one by one, and the keys with
    many are a product with a matrix of zeros and ones.
    """
    order = key.argsort(kind="stable")
    ordered = key.take(order)
    if len(key) > len(values):
        order %= len(values)
    new = np.empty(len(key), bool)
    new[0] = True
    np.not_equal(ordered[1:], ordered[:-1], out=new[1:])
    first = np.flatnonzero(new)
    size = np.empty_like(first)
    np.subtract(first[1:], first[:-1], out=size[:-1])
    size[-1] = len(key) - first[-1]
    out = values.take(order.take(first), axis=0)
    some = np.flatnonzero((size > 1) & (size <= few))
    for k in range(1, few):
        out[some] += values.take(order.take(first.take(some) + k), axis=0)
        some = some[size.take(some) > k + 1]
    many = np.flatnonzero(size > few)
    for low in range(0, len(many), MANY):
        own = many[low : low + MANY]
        n = size.take(own)
        whose = np.repeat(np.arange(len(own)), n)
        at = np.arange(len(whose)) + np.repeat(first.take(own) - np.cumsum(n) + n, n)
        member = np.zeros((len(own), len(whose)), values.dtype)
        member[whose, np.arange(len(whose))] = 1
        out[own] = member @ values.take(order.take(at), axis=0)
    return out, ordered.take(first), size


def _whole_rows(values: np.ndarray) -> np.ndarray:
    """Each row as one item: rows are then copied as a whole."""
    return values.view(f"V{values.shape[1] * values.itemsize}")[:, 0]


class Learner:
    """AdaGrad over one task's rows, with one step size for each weight row."""

    def __init__(self, model: Model):
        self.model = Model(model.vocabulary, model.weights.copy(), model.inner.copy())
        self.squares = [np.full(n, 1e-2, np.float32) for n in (ROWS, INNER_ROWS)]
        self.met = [np.zeros(n, np.int64) for n in (ROWS, INNER_ROWS)]

    def step(self, numbers: np.ndarray, before: np.ndarray, before_that: np.ndarray) -> None:
        m, v = self.model, self.model.vocabulary
        bias = _for_each(v.bias, min(STEP, len(numbers)))
        for low in range(0, len(numbers), STEP):
            n, b, bb = (x[low : low + STEP] for x in (numbers, before, before_that))
            k = v.classes.take(n)
            self._towards(0, m.weights, m.histories.rows(b, bb), bias[: len(k)], k)
            shared = np.flatnonzero(k >= OWN)
            if len(shared):
                k = k[shared]
                self._towards(1, m.inner, m.histories.inner_rows(b[shared], bb[shared], k), v.inner_bias.take(k, axis=0), v.slots.take(n[shared]))

    def _towards(self, table: int, weights: np.ndarray, rows: tuple[np.ndarray, ...], bias: np.ndarray, truth: np.ndarray) -> None:
        gradient, total = _softmax(weights, rows, bias)
        gradient *= 1 / total
        gradient.ravel()[np.arange(len(truth)) * gradient.shape[1] + truth] -= 1
        squares, met = self.squares[table], self.met[table]
        # Rows that a batch meets more than once take the sum of their gradients in one step.
        change, at, times = summed_by(gradient, np.concatenate(rows))
        at = at.astype(np.intp)
        grown = squares.take(at) + np.einsum("ij,ij->i", change, change) / weights.shape[1]
        squares[at] = grown
        met[at] += times
        change *= (-RATE / np.sqrt(grown))[:, None]
        change += weights.take(at, axis=0)
        _whole_rows(weights)[at] = _whole_rows(change)

    def blocks(self) -> Iterator[tuple[int, bytes, bytes]]:
        """(block, times met, weights) of the blocks with rows that were met; blocks of both tables count on."""
        for first, met, weights in ((0, self.met[0], self.model.weights), (ROWS // ROW_BLOCK, self.met[1], self.model.inner)):
            for k in range(len(met) // ROW_BLOCK):
                own = slice(k * ROW_BLOCK, (k + 1) * ROW_BLOCK)
                if met[own].any():
                    yield first + k, met[own].astype("<f8").tobytes(), weights[own].astype("<f2").tobytes()


def _with_ends(numbers: np.ndarray, sizes: np.ndarray, end: int) -> pa.Array:
    """The numbers of each text and the end's, as bytes."""
    ends = np.cumsum(sizes + 1) - 1
    out = np.empty(len(numbers) + len(sizes), "<i4")
    inside = np.ones(len(out), bool)
    inside[ends] = False
    out[inside], out[ends] = numbers, end
    starts = np.concatenate([[0], ends + 1])
    return pa.Array.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer((starts * 4).astype(np.int32)), pa.py_buffer(out)])


def _times(texts: np.ndarray, words: pa.DictionaryArray, n: int, ends: bool) -> tuple[pa.Array, pa.Array]:
    """Of n texts, each one's distinct words and their times; ``texts`` has the text of each word. ``ends`` adds the end to all."""
    every = pa.concat_arrays([words.dictionary, pa.array([END], pa.binary())])
    pairs = texts * len(every) + words.indices.to_numpy()
    if ends:
        pairs = np.append(pairs, np.arange(n) * len(every) + len(every) - 1)
    found, times = np.unique(pairs, return_counts=True)
    starts = pa.array(np.searchsorted(found // len(every), np.arange(n + 1)), pa.int32())
    own = every.take(pa.array(found % len(every)))
    return pa.ListArray.from_arrays(starts, own), pa.ListArray.from_arrays(starts, pa.array(times, pa.int32()))


def numbered(docs: DataFrame, vocabulary: Vocabulary) -> DataFrame:
    """Every text as numbers, stored: row, doc_id, trained, ids, and its words outside the head with their times.

    Tail words have numbers too, by class and hash; their counts are joined by word.
    """
    spark = docs.sparkSession
    held = spark.sparkContext.broadcast(vocabulary)
    kind = docs.schema["doc_id"].dataType
    schema = pa.schema([("row", pa.int64()), ("doc_id", _arrow(kind)), ("trained", pa.bool_()), ("ids", pa.binary()), ("rare", pa.list_(pa.binary())), ("times", pa.list_(pa.int32()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        v = held.value
        head = pa.array(v.words, pa.binary())
        row = TaskContext.get().partitionId() << 33
        for some in lots(batches):
            words, sizes = split(some.column("text"))
            numbers, at, tails = v.numbers_of(words, head)
            ids = _with_ends(numbers, sizes, v.end)
            rare, times = _times(np.repeat(np.arange(len(sizes)), sizes).take(at), tails, len(sizes), v.end >= len(head))
            rows = pa.array(np.arange(row, row + len(sizes)))
            yield pa.RecordBatch.from_arrays([rows, some.column("doc_id"), some.column("trained"), ids, rare, times], schema=schema)
            row += len(sizes)

    columns = f"row long, doc_id {kind.simpleString()}, trained boolean, ids binary, rare array<binary>, times array<int>"
    return SharedTable(docs.select("doc_id", in_training(F.col("doc_id")).alias("trained"), "text").mapInArrow(run, columns), "maxent-numbers").read()


def _token_batches(lots: Iterable[bytes], end: int, size: int = 1 << 16) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Numbers, both histories and starts of texts, some texts at a time."""
    held: list[np.ndarray] = []
    n = 0
    for ids in lots:
        held.append(np.frombuffer(ids, "<i4"))
        n += len(held[-1])
        if n >= size:
            yield _joined(held, end)
            held, n = [], 0
    if held:
        yield _joined(held, end)


def _joined(held: list[np.ndarray], end: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    numbers = np.concatenate(held).astype(np.int64)
    starts = np.cumsum([0, *map(len, held[:-1])])
    return numbers, *histories_of(numbers, starts, end), starts


def train(numbers: DataFrame, vocabulary: Vocabulary) -> Model:
    """One round of distributed updates over all training rows of the numbered texts."""
    spark = numbers.sparkSession
    held = spark.sparkContext.broadcast(vocabulary)
    schema = pa.schema([("block", pa.int64()), ("salt", pa.int64()), ("met", pa.binary()), ("weights", pa.binary())])

    def learn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        learner: Learner | None = None
        for ids, before, before_that, _ in _token_batches((x for (x,) in rows_of(batches, "ids")), held.value.end):
            learner = learner or Learner(Model(held.value))
            learner.step(ids, before, before_that)
        salt = TaskContext.get().partitionId() % 64
        return batched(((k, salt, met, w) for k, met, w in learner.blocks()) if learner else iter(()), schema)

    learners = max(1, round(vocabulary.total / LEARNER_TOKENS))
    found = numbers.where("trained").select("ids").coalesce(learners).mapInArrow(learn, "block long, salt long, met binary, weights binary")
    by_salt = _merged(found.repartition("block", "salt"), "<f2")
    rows = _merged(by_salt.repartition("block"), "<f4").collect()
    model = Model(vocabulary)
    for x in rows:
        table, at = (model.weights, x.block) if x.block < ROWS // ROW_BLOCK else (model.inner, x.block - ROWS // ROW_BLOCK)
        table[at * ROW_BLOCK : (at + 1) * ROW_BLOCK] = np.frombuffer(x.weights, "<f4").reshape(ROW_BLOCK, -1)
    return model


def _merged(found: DataFrame, kind: str) -> DataFrame:
    """Averages by times met, one row for each block in a partition."""
    schema = pa.schema([("block", pa.int64()), ("salt", pa.int64()), ("met", pa.binary()), ("weights", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for block, met, weights in rows_of(batches, "block", "met", "weights"):
            n, w = np.frombuffer(met, "<f8"), np.frombuffer(weights, kind).reshape(ROW_BLOCK, -1)
            if block not in sums:
                sums[block] = np.zeros(ROW_BLOCK), np.zeros(w.shape)
            total, weighed = sums[block]
            total += n
            weighed += w * n[:, None]
        return batched(((k, 0, n.tobytes(), (w / np.maximum(n, 1)[:, None]).astype("<f4").tobytes()) for k, (n, w) in sums.items()), schema)

    return found.mapInArrow(run, "block long, salt long, met binary, weights binary")


def score(numbers: DataFrame, model: Model, counts: DataFrame) -> DataFrame:
    """doc_id, trained, n_tokens, n_known, base_score and score (log10 probabilities of the text) of the numbered texts."""
    spark = numbers.sparkSession
    held = spark.sparkContext.broadcast(model)
    kind = numbers.schema["doc_id"].dataType
    schema = pa.schema([("row", pa.int64()), ("doc_id", _arrow(kind)), ("trained", pa.bool_()), ("n_tokens", pa.int64()), ("head_known", pa.int64()), ("base", pa.float64()), ("own", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = held.value
        v = model.vocabulary
        heads = len(v.words)
        seen: list[tuple] = []

        def lots() -> Iterator[bytes]:
            for *who, ids in rows_of(batches, "row", "doc_id", "trained", "ids"):
                seen.append(who)
                yield ids

        def out() -> Iterator[tuple]:
            for ids, before, before_that, starts in _token_batches(lots(), v.end):
                known = ids < heads
                base = np.where(known, v.base[np.minimum(ids, max(0, heads - 1))] if heads else 0.0, -v.norm)
                sums = [np.add.reduceat(x, starts).tolist() for x in (known.astype(np.int64), base, model.scores(ids, before, before_that))]
                sizes = np.diff(np.append(starts, len(ids))).tolist()
                yield from zip(*zip(*seen, strict=True), sizes, *sums, strict=True)
                seen.clear()

        return batched(out(), schema, 8192)

    scored = numbers.select("row", "doc_id", "trained", "ids").mapInArrow(run, f"row long, doc_id {kind.simpleString()}, trained boolean, n_tokens long, head_known long, base double, own double")
    rare = numbers.select("row", F.explode(F.arrays_zip("rare", "times")).alias("x")).select("row", F.col("x.rare").alias("word"), F.col("x.times").alias("times"))
    # A word outside the head has a bounded share of all tokens: these keys are not hot.
    met = rare.join(counts, "word").groupBy("row").agg(F.sum("times").alias("more_known"), F.sum(F.col("times") * F.log10(F.col("c") + 1)).alias("more"))
    more = F.coalesce("more", F.lit(0.0))
    return scored.join(met, "row", "left").select(
        "doc_id", "trained", "n_tokens", (F.col("head_known") + F.coalesce("more_known", F.lit(0))).alias("n_known"), (F.col("base") + more).alias("base_score"), (F.col("own") + more).alias("score")
    )


def in_training(doc_id: Column) -> Column:
    return is_trained_on(doc_id, DIVISOR, HELD_OUT)


def fit(docs: DataFrame) -> tuple[Model, DataFrame, DataFrame]:
    """The model of the training rows, the table of their word counts, and all texts as numbers."""
    counts = SharedTable(count_words(docs.where(in_training(F.col("doc_id")))), "maxent-counts").read()
    v = vocabulary(counts)
    numbers = numbered(docs, v)
    return train(numbers, v), counts, numbers


def digest(docs: DataFrame) -> DataFrame:
    model, counts, numbers = fit(docs)
    return score(numbers, model, counts).select("doc_id", (~F.col("trained")).alias("held_out"), "n_tokens", "n_known", F.lit(model.vocabulary.total).cast("long").alias("train_tokens"), "base_score", "score")
