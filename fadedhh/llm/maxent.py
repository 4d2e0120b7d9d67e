"""Language-model scores from a hashed maximum-entropy model with a class-factored softmax over the whole vocabulary.

Tokens are the space-delimited words of the lower-cased text and one end. The most frequent words (and the end)
have outputs of their own; every other word belongs to one of some sixty group outputs, by the company it keeps (a cluster of
frequent words near it) and by its frequency. The softmax over the outputs has two factors, class and member, both log-linear
in a bias, the output before, the output before that (a skip) and their hashed pair.

Within a group a word has its add-one unigram, raised by a feature for each hashed pair of the word before and itself that
was seen. These features exclude each other given the word before, so their maximum-entropy weights have a
closed form: a seen pair gets its count, and all words of the group share as many counts as there are kinds of pairs (the sum over the vocabulary is 1 in every context).

The softmax is trained data-parallel: every partition runs gradient updates over its own documents from the common weights,
differences are averaged by tokens, and the next round goes on from there with the other documents; each training
document is used once. Positions are grouped by context and output first, so gradients are dense in few contexts.

Counts of words and of pairs stay distributed. What is broadcast is bounded: the dictionary of the commonest words, the
commonest pairs, the weights. Rarer words get their counts and rarer pairs their weights by a join, so what is broadcast changes no score.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadedhh.shipping import arrow_map

from . import textbytes as tb
from .common import release, settle

CLASSES, MEMBERS = 16, 32
OUTPUTS = CLASSES * MEMBERS
PAIRS = 1024
#: Words that have a group, at most.
DICTIONARY = (1 << 18) - 1
#: Frequent words that are clustered, clusters, and frequency steps (doublings) of a group.
CENTRES, CLUSTERS, STEPS = 128, 7, 9
#: Group 0 holds the words without company and those beyond the dictionary.
GROUPS = 1 + CLUSTERS * STEPS
#: Pairs of words whose weight every task holds, at most; the others' come by a join.
PAIR_WEIGHTS = 1 << 21
ROUNDS = 2
BATCH = 1 << 15
SLICES = 64
END = np.uint64(1)
START_ID = OUTPUTS
FEATURES = 2 * (OUTPUTS + 1) + PAIRS + 1
#: The low bits of a pair's key: its word.
LAST = (1 << 18) - 1
LN10 = float(np.log(10.0))


def tokens(column: pa.Array, budget: int = 1 << 21):
    """Yields (first row, token hashes with one end per row, tokens per row) over runs of rows."""
    data, offsets = tb.raw(column)
    for i, j in tb.runs_of_rows(offsets, budget):
        h, count = tb.words(data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], tb.SPACED)
        ends = np.cumsum(count) + np.arange(j - i)
        out = np.empty(len(h) + j - i, np.uint64)
        word = np.ones(len(out), bool)
        word[ends] = False
        out[word] = np.where(h <= END, h + np.uint64(2), h)
        out[ends] = END
        yield i, out, count + 1


def beside(count: np.ndarray, reach: int):
    """Yields (slice, slice) pairs of positions up to ``reach`` apart, with a mask of those in one row."""
    row = np.repeat(np.arange(len(count)), count)
    for d in range(1, reach + 1):
        a, b = slice(None, -d), slice(d, None)
        yield a, b, (row[a] == row[b])


def history(ids: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The two outputs before each token within its row."""
    first = np.cumsum(count) - count
    one = np.concatenate([[START_ID], ids[:-1]])
    one[first] = START_ID
    two = np.concatenate([[START_ID], one[:-1]])
    two[first] = START_ID
    return one, two


def features(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Rows of the weight tables: previous word, skip word, hashed pair, bias."""
    pair = (tb.mix64((two * (OUTPUTS + 1) + one).astype(np.uint64)) % np.uint64(PAIRS)).astype(np.int64)
    return np.stack([one, OUTPUTS + 1 + two, 2 * (OUTPUTS + 1) + pair, np.full(len(one), FEATURES - 1)])


def _softmax(w: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(z, exp(z), its sums) with z the sum of the weight rows named by a column of ``rows``, less its maximum where it would leave the
    range of floats."""
    z = w.take(rows[0], axis=0)
    for r in rows[1:]:
        z += w.take(r, axis=0)
    one = np.ones(z.shape[1], np.float32)
    with np.errstate(over="ignore"):
        e = np.exp(z)
        total = e @ one
    if not (np.isfinite(total).all() and (total > 1e-20).all()):
        z -= z.max(axis=1, keepdims=True)
        e = np.exp(z)
        total = e @ one
    return z, e, total


def _climb(w: np.ndarray, squares: np.ndarray, rows: np.ndarray, g: np.ndarray, rate: float) -> None:
    """Adds the gradient ``g`` to the weight rows named by each line of ``rows``, with adaptive steps."""
    for r in rows.astype(np.uint16):  # there are fewer rows than 2 ** 16, and short numbers are sorted by radix
        order = np.argsort(r, kind="stable")
        f = r[order]
        at = _starts(f)
        f = f[at]
        total = np.add.reduceat(g.take(order, axis=0).view(np.complex64), at, axis=0).view(np.float32)  # two columns at once
        s = squares.take(f, axis=0)
        s += total * total
        squares[f] = s
        w[f] += rate * total / (np.sqrt(s) + 1e-6)


class Model:
    """Weights of both softmax layers: classes by feature, members by (feature, class). Only the classes that occur in a
    context are worked out for it; the others have no part in its likelihood's second factor."""

    def __init__(self, weights: np.ndarray):
        self.w = weights
        self.of_class = weights[: FEATURES * CLASSES].reshape(FEATURES, CLASSES)
        self.of_member = weights[FEATURES * CLASSES :].reshape(FEATURES * CLASSES, MEMBERS)

    @classmethod
    def from_counts(cls, count: np.ndarray, used: np.ndarray | bool = True) -> Model:
        """Bias at the unigram distribution, all else zero. Outputs not ``used``, to which no word belongs, get no mass."""
        m = cls(np.zeros(FEATURES * (CLASSES + OUTPUTS), np.float32))
        c = np.where(used, count + 0.5, 1e-30)
        m.of_class[-1] = np.log(c.reshape(CLASSES, MEMBERS).sum(axis=1) / c.sum())
        m.of_member[-CLASSES:] = np.log(c).reshape(CLASSES, MEMBERS)
        return m

    @staticmethod
    def grouped(ids: np.ndarray, one: np.ndarray, two: np.ndarray) -> tuple:
        """(feature rows per context, context of each (context, class), class of it, its member rows, place of each token)."""
        context, back = np.unique(two * (OUTPUTS + 1) + one, return_inverse=True)
        rows = features(context % (OUTPUTS + 1), context // (OUTPUTS + 1))
        pair, place = np.unique(back * CLASSES + ids // MEMBERS, return_inverse=True)
        own, cls = pair // CLASSES, pair % CLASSES
        return rows, own, cls, rows[:, own] * CLASSES + cls, place

    def __reduce__(self):
        return Model, (self.w,)

    def score(self, ids: np.ndarray, one: np.ndarray, two: np.ndarray, step: int = 1 << 16) -> np.ndarray:
        """Natural log probability of each output in its context, ``step`` positions at a time."""
        out = np.empty(len(ids))
        for lo in range(0, len(ids), step):
            part = slice(lo, lo + step)
            rows, own, cls, deep, place = self.grouped(ids[part], one[part], two[part])
            z, _, total = _softmax(self.of_class, rows)
            out[part] = (z[own, cls] - np.log(total)[own])[place]
            z, _, total = _softmax(self.of_member, deep)
            out[part] += z.reshape(-1).take(place * MEMBERS + ids[part] % MEMBERS) - np.log(total)[place]
        return out

    def update(self, ids: np.ndarray, one: np.ndarray, two: np.ndarray, squares: Model, rate: float) -> None:
        """One adaptive gradient step on the log likelihood of a batch."""
        rows, own, cls, deep, place = self.grouped(ids, one, two)
        seen = np.bincount(place * MEMBERS + ids % MEMBERS, minlength=len(own) * MEMBERS).reshape(-1, MEMBERS).astype(np.float32)
        total = seen.sum(axis=1)
        by_class = np.zeros((rows.shape[1], CLASSES), np.float32)
        by_class[own, cls] = total
        _, top, norm = _softmax(self.of_class, rows)
        top = (by_class - (by_class.sum(axis=1) / norm)[:, None] * top) / len(ids)
        _, low, norm = _softmax(self.of_member, deep)
        low = (seen - (total / norm)[:, None] * low) / len(ids)
        _climb(self.of_class, squares.of_class, rows, top, rate)
        _climb(self.of_member, squares.of_member, deep, low, rate)


def _train(batches, weights: np.ndarray, book: Dictionary, rate: float, batch: int):
    """Gradient updates over one partition; yields the token-weighted differences in slices."""
    model, squares, used = Model(weights.copy()), Model(np.zeros_like(weights)), 0
    held: list = []
    size = 0

    def learn():
        ids, one, two = (np.concatenate(x) for x in zip(*held))
        for lo in range(0, len(ids), batch):
            part = slice(lo, lo + batch)
            model.update(ids[part], one[part], two[part], squares, rate)

    for b in batches:
        for _, h, count in tokens(b.column(0)):
            ids = book.outputs(book.find(h))
            held.append((ids, *history(ids, count)))
            size += len(ids)
            used += len(ids)
            if size >= 4 * batch:
                learn()
                held, size = [], 0
    if size:
        learn()
    if used:
        change = (model.w - weights).astype(np.float16).reshape(-1)
        for s, part in enumerate(np.array_split(change, SLICES)):
            yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([used], pa.int64()), pa.array([part.tobytes()])], names=["slice", "n", "part"])


def _average(batches):
    """Weighted sums per slice, held one slice at a time whatever the number of partitions."""
    total: dict = {}
    for b in batches:
        for s, n, part in zip(*(c.to_pylist() for c in b.columns)):
            x, m = total.get(s, (0, 0))
            total[s] = (x + np.frombuffer(part, np.float16).astype(np.float64) * n, m + n)
    for s, (x, n) in total.items():
        yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([n], pa.int64()), pa.array([(x / n).astype(np.float32).tobytes()])], names=["slice", "n", "part"])


class Index:
    """Places of 64-bit keys in an array of distinct ones, found by the leading bits of the mixed key. Only the keys are pickled, as every
    executor has a broadcast on its disk; the rest is made where it is first used, without sorting if the keys are in the order of ``mixed``."""

    def __init__(self, keys: np.ndarray):
        self.keys, self.mixed = keys, None

    def __reduce__(self):
        return Index, (self.keys,)

    @staticmethod
    def order(keys: np.ndarray) -> np.ndarray:
        return np.argsort(tb.mix64(keys.view(np.uint64)))

    def _make(self) -> None:
        mixed, self.place = tb.mix64(self.keys.view(np.uint64)), None
        if (mixed[1:] < mixed[:-1]).any():
            self.place = np.argsort(mixed).astype(np.int32)
            mixed = mixed[self.place]
        self.shift = np.uint64(64 - min(22, max(1, len(mixed).bit_length() + 1)))
        size = np.bincount((mixed >> self.shift).view(np.int64), minlength=1 << (64 - int(self.shift)))
        self.first = np.zeros(len(size) + 1, np.int32)
        np.cumsum(size, out=self.first[1:])
        self.mixed = mixed

    def __call__(self, keys: np.ndarray) -> np.ndarray:
        """Places, -1 for keys that are not in the array."""
        out = np.full(len(keys), -1)
        if not len(self.keys):
            return out
        if self.mixed is None:
            self._make()
        mixed = tb.mix64(keys.view(np.uint64))
        lead = (mixed >> self.shift).astype(np.int64)
        at, end = self.first[lead], self.first[lead + 1]
        left = np.flatnonzero(at < end)
        at, end, mixed = at[left], end[left], mixed[left]
        while len(left):
            hit = self.mixed[at] == mixed
            out[left[hit]] = at[hit] if self.place is None else self.place[at[hit]]
            on = np.flatnonzero(~hit & (at + 1 < end))
            left, at, end, mixed = left[on], at[on] + 1, end[on], mixed[on]
        return out


class Dictionary:
    """The commonest words, sorted by hash, with their counts and outputs; ``full`` if there are no others."""

    def __init__(self, w: np.ndarray, c: np.ndarray, full: bool, total: int, kinds: int):
        order = np.argsort(w)
        self.word, self.count, self.full, self.total, self.kinds = w[order], c[order], full, total, kinds
        self.rank = np.empty(len(w), np.int64)
        self.rank[order] = np.arange(len(w))  # places in the sorted arrays, commonest word first
        self.index = Index(self.word)
        self.output = np.zeros(len(w), np.int16)
        self.fill(np.full(len(w), -1))

    def __getstate__(self) -> dict:
        return {**self.__dict__, "rank": None}  # of use on the driver only

    def fill(self, cluster: np.ndarray) -> None:
        """Sets outputs and the mass of every group, the unseen included in group 0, from the words' clusters."""
        step = np.minimum(np.frexp(self.count.astype(float))[1] - 1, STEPS - 1)
        self.output = np.where(cluster < 0, 0, 1 + cluster * STEPS + step).astype(np.int16)
        own = self.rank[: OUTPUTS - GROUPS + 1]
        own = np.concatenate([own[self.word[own] == END], own[self.word[own] != END]])[: OUTPUTS - GROUPS]
        self.output[own] = GROUPS + np.arange(len(own))
        self.mass = np.bincount(self.output, self.count + 1.0, minlength=OUTPUTS)
        self.mass[0] = self.total + self.kinds + 1 - self.mass[1:].sum()

    def find(self, h: np.ndarray) -> np.ndarray:
        """Places of tokens, -1 for those not in the dictionary."""
        return self.index(h)

    def outputs(self, place: np.ndarray) -> np.ndarray:
        return np.where(place < 0, 0, self.output[place]).astype(np.int64) if len(self.word) else np.zeros(len(place), np.int64)

    def counts(self, place: np.ndarray) -> np.ndarray:
        return np.where(place < 0, 0, self.count[place]) if len(self.word) else np.zeros(len(place), np.int64)


def pair_keys(h: np.ndarray, count: np.ndarray, place: np.ndarray, ids: np.ndarray) -> np.ndarray:
    """Key of every token with the one before it: 38 bits of that one's hash, 7 of the token's group, 18 of its place (all ones
    for a word beyond the dictionary, which no counted pair has)."""
    before = np.concatenate([np.zeros(1, np.uint64), h[:-1]])
    before[np.cumsum(count) - count] = 0
    last = np.where(place < 0, (1 << 18) - 1, np.minimum(place, (1 << 18) - 1)).astype(np.uint64)
    return (((tb.mix64(before) >> np.uint64(26)) << np.uint64(25)) | (ids.astype(np.uint64) << np.uint64(18)) | last).astype(np.int64)


class Pairs:
    """The commonest pairs with their counts, and per word before and group the counts of all pairs, with and without their kinds. ``rest``
    is the table of all pairs (key, n); without one there are no others."""

    def __init__(self, key: np.ndarray, n: np.ndarray, context: np.ndarray, total: np.ndarray, kept: np.ndarray, rest: DataFrame | None = None):
        order, other = Index.order(key), Index.order(context)
        self.key, self.n = key[order], n[order].astype(np.int32)
        self.context, self.total, self.kept = context[other], total[other], kept[other]
        self.pair, self.before = Index(self.key), Index(self.context)
        self.rest, self.more = rest, rest is not None

    def __getstate__(self) -> dict:
        return {**self.__dict__, "rest": None}

    def __call__(self, key: np.ndarray, unigram: np.ndarray) -> np.ndarray:
        """Probabilities within the group, from those without the pairs; what ``missing`` names is not in them."""
        if not len(self.key):
            return unigram
        k, z = self.pair(key), self.before(key >> 18)
        n = np.where(k >= 0, self.n[k], 0)
        return np.where(z >= 0, (n + (self.total[z] - self.kept[z]) * unigram) / self.total[z], unigram)

    def missing(self, key: np.ndarray) -> np.ndarray:
        """Which pairs have something in ``rest``: those not held, for which there is no need if their context is held and their
        word is beyond the dictionary."""
        if not len(self.key):
            return np.ones(len(key), bool)
        return (self.pair(key) < 0) & ((key & LAST != LAST) | (self.before(key >> 18) < 0))


class Counts:
    """Token counts of the training rows: a settled table, its totals, and the dictionary of the commonest."""

    def __init__(self, train: DataFrame, text: str):
        def run(batches):
            for b in batches:
                got = [np.unique(h, return_counts=True) for _, h, _ in tokens(b.column(0), 1 << 21)]
                if got:
                    h, c = np.concatenate([x[0] for x in got]), np.concatenate([x[1] for x in got])
                    u, back = np.unique(h, return_inverse=True)
                    yield pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(np.bincount(back, c).astype(np.int64))], names=["w", "c"])

        part = arrow_map(train.select(F.col(text).alias("t")), run, "w long, c long")
        self.table = settle(part.groupBy("w").agg(F.sum("c").alias("c")))
        n, v = self.table.agg(F.sum("c"), F.count("*")).first()
        self.n, self.v = int(n or 0), int(v)
        top = self.table.orderBy(F.desc("c"), "w").limit(DICTIONARY).toArrow()
        self.book = Dictionary(top.column("w").to_numpy().view(np.uint64), top.column("c").to_numpy().astype(np.int64), self.v <= DICTIONARY, self.n, self.v)


def _sums(batches, size: int, add) -> pa.RecordBatch:
    """Counts per cell of an array of fixed size, over a partition: rows (k, n) of the cells that are not 0."""
    total = np.zeros(size, np.int64)
    for b in batches:
        for _, h, count in tokens(b.column(0)):
            add(total, h, count)
    k = np.flatnonzero(total)
    return pa.RecordBatch.from_arrays([pa.array(k), pa.array(total[k])], names=["k", "n"])


def _summed(train: DataFrame, text: str, size: int, add) -> np.ndarray:
    """The same over all partitions, on the driver; its size does not depend on the data."""
    rows = arrow_map(train.select(F.col(text).alias("t")), lambda it: iter([_sums(it, size, add)]), "k long, n long")
    got = rows.groupBy("k").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(size)
    out[got.column("k").to_numpy()] = got.column("n").to_numpy()
    return out


def centres(near: np.ndarray, clusters: int = CLUSTERS) -> np.ndarray:
    """Clusters of the frequent words by what stands near them: k-means of positive association, from the words that are
    most unlike each other."""
    p = np.maximum(np.log((near + 0.5) * near.sum() / np.outer(near.sum(1) + 1, near.sum(0) + 1)), 0) if near.sum() else near
    p = p / (np.linalg.norm(p, axis=1, keepdims=True) + 1e-9)
    mid = p[:1]
    while len(mid) < clusters:
        mid = np.concatenate([mid, p[[np.argmin((p @ mid.T).max(axis=1))]]])
    for _ in range(20):
        own = (p @ mid.T).argmax(axis=1)
        mid = np.stack([p[own == k].mean(axis=0) if (own == k).any() else mid[k] for k in range(clusters)])
        mid /= np.linalg.norm(mid, axis=1, keepdims=True) + 1e-9
    return own


def cluster_words(train: DataFrame, book: Dictionary, text: str) -> np.ndarray:
    """Cluster of every word of the dictionary, -1 for those that no clustered word is near: that which stands near it more often than its
    frequency would have it."""
    context = train.sparkSession.sparkContext
    top = book.rank[: CENTRES + 1]
    top = top[book.word[top] != END][:CENTRES]
    number = np.full(len(book.word) + 1, -1, np.int16)
    number[top] = np.arange(len(top))
    held = context.broadcast((book.index, number))

    def find(h):
        index, number = held.value
        place = index(h)
        return place, number[place]

    def meet(total, h, count):
        _, f = find(h)
        for a, b, same in beside(count, 2):
            ok = same & (f[a] >= 0) & (f[b] >= 0)
            total += np.bincount(f[a][ok] * CENTRES + f[b][ok], minlength=CENTRES * CENTRES)

    if not len(top):
        return np.full(len(book.word), -1)
    near = _summed(train, text, CENTRES * CENTRES, meet).reshape(CENTRES, CENTRES)[: len(top), : len(top)]
    own = centres(near + near.T)
    cluster_of = np.append(own, -1)
    size = len(book.word) * CLUSTERS

    def vote(total, h, count):
        place, f = find(h)
        c = cluster_of[f]
        for a, b, same in beside(count, 2):
            for x, y in ((a, b), (b, a)):
                ok = same & (place[x] >= 0) & (c[y] >= 0)
                np.add.at(total, place[x][ok] * CLUSTERS + c[y][ok], 1)

    votes = _summed(train, text, size, vote).reshape(-1, CLUSTERS)
    held.destroy()
    share = np.bincount(own, book.count[top], minlength=CLUSTERS) / max(1, book.count[top].sum())
    best = (votes / np.maximum(votes.sum(axis=1, keepdims=True), 1) / np.sqrt(share + 1e-3)).argmax(axis=1)
    return np.where(votes.sum(axis=1) > 0, best, -1)


def _starts(x: np.ndarray) -> np.ndarray:
    """Where runs of equal numbers begin."""
    return np.flatnonzero(np.concatenate([[True], x[1:] != x[:-1]])) if len(x) else np.zeros(0, np.int64)


def _pair_table(batches):
    """From counts sorted by pair, a context's pairs next to each other: rows (key, n, kinds, total) of every pair, the last two of its
    context. Holds one context's kinds of pairs, at most the dictionary, and a batch."""
    k, n = np.zeros(0, np.int64), np.zeros(0, np.int64)

    def rows(k, n):
        at = _starts(k >> 18)
        kinds = np.diff(np.append(at, len(k)))
        cols = k, n, np.repeat(kinds, kinds), np.repeat(np.add.reduceat(n, at) + kinds, kinds)
        return pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["key", "n", "kinds", "total"])

    for b in batches:
        k, n = (np.concatenate([a, b.column(c).to_numpy()]) for c, a in enumerate((k, n)))
        if not len(k):
            continue
        at = _starts(k)
        k, n = k[at], np.add.reduceat(n, at)
        cut = int(np.searchsorted(k, (k[-1] >> 18) << 18))
        if cut:
            yield rows(k[:cut], n[:cut])
        k, n = k[cut:], n[cut:]
    if len(k):
        yield rows(k, n)


def _weights_of_rest(batches, book: Dictionary, pairs: Pairs):
    """From rows (s, v) sorted by s, whose bits are context, whether it is asked for, and word: counted pairs with their counts, then
    those asked for with their rows, the sums of the logarithms that these lack by row. Holds one context's kinds of pairs and a batch."""
    k, n = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for b in batches:
        s, v = b.column(0).to_numpy(), b.column(1).to_numpy()
        if not len(s):
            continue
        asked = (s >> 18) & 1 == 1
        k, n = np.concatenate([k, s[~asked]]), np.concatenate([n, v[~asked]])
        x, want, row = k >> 19, s[asked], v[asked]
        at = _starts(x)
        if len(at) and len(want):
            kinds = np.diff(np.append(at, len(k)))
            total = np.add.reduceat(n, at) + kinds
            z = np.minimum(np.searchsorted(x[at], want >> 19), len(at) - 1)
            on = np.flatnonzero(x[at][z] == want >> 19)  # after a word that no pair of this group has, nothing is added
            want, row, z = want[on], row[on], z[on]
            pair = want ^ (1 << 18)
            j = np.minimum(np.searchsorted(k, pair), len(k) - 1)
            place = np.minimum(want & LAST, len(book.word) - 1)
            u = (book.count[place] + 1.0) / book.mass[book.output[place]]
            log = np.where(k[j] == pair, np.log10(1 + n[j] / (kinds[z] * u)), 0.0)
            log += np.where(pairs.before((want >> 19) & ((1 << 45) - 1)) < 0, np.log10(kinds[z] / total[z]), 0.0)
            row, back = np.unique(row, return_inverse=True)
            yield pa.RecordBatch.from_arrays([pa.array(row), pa.array(np.bincount(back, log, minlength=len(row)).astype(float))], names=["r", "mv"])
        k, n = k[x == s[-1] >> 19], n[x == s[-1] >> 19]


def count_pairs(train: DataFrame, book, text: str, limit: int = PAIR_WEIGHTS, portion: int = 1 << 22) -> Pairs:
    """All pairs of a word and a word of a group after it are counted and have their weights. The commonest are held by every task, down
    to the count at which no more than ``limit`` are; all others stay in a table that scores are joined with."""

    def run(batches):
        book_, keys, size = book.value, [], 0

        def counted():
            k, n = np.unique(np.concatenate(keys), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(k), pa.array(n.astype(np.int64))], names=["k", "n"])

        for b in batches:
            for _, h, count in tokens(b.column(0)):
                place = book_.find(h)
                ids = book_.outputs(place)
                keys.append(pair_keys(h, count, place, ids)[(place >= 0) & (ids < GROUPS)])
                size += len(keys[-1])
                if size >= portion:
                    yield counted()
                    keys, size = [], 0
        if size:
            yield counted()

    part = arrow_map(train.select(F.col(text).alias("t")), run, "k long, n long").repartition(F.shiftright("k", 18)).sortWithinPartitions("k")
    pairs = settle(arrow_map(part, _pair_table, "key long, n long, kinds long, total long"))
    del part
    release(train.sparkSession)
    level = F.when(F.col("n") < 64, F.col("n")).otherwise(F.pow(F.lit(2.0), F.floor(F.log2("n"))).cast("long"))
    least, room = 1, limit
    for m, n in sorted(((r["m"], r["count"]) for r in pairs.groupBy(level.alias("m")).count().collect()), reverse=True):
        room -= n
        if room < 0:
            least = 2 * m if m >= 64 else m + 1
            break
    held = pairs.where(F.col("n") >= least).select("key", "n", "kinds", "total").toArrow()
    key, n, kinds, total = (held.column(c).to_numpy() for c in range(4))
    context, at = np.unique(key >> 18, return_index=True)
    return Pairs(key, n, context, total[at].astype(np.float64), (total - kinds)[at].astype(np.float64), pairs.select("key", "n") if room < 0 else None)


def train_model(train: DataFrame, counts: Counts, text: str, doc_id: str, rounds: int = ROUNDS, rate: float = 0.5, batch: int = BATCH) -> tuple[Model, Pairs]:
    book = counts.book
    book.fill(cluster_words(train, book, text))
    context = train.sparkSession.sparkContext
    held = context.broadcast(book)
    seen = np.bincount(book.output, book.count, minlength=OUTPUTS)
    seen[0] = counts.n - seen[1:].sum()
    model = Model.from_counts(seen, book.mass > 0)
    parts = int(train.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    for r in range(rounds):
        w = context.broadcast(model.w)
        mine = train.where(F.pmod(F.xxhash64(doc_id), F.lit(rounds)) == r).select(F.col(text).alias("t"))
        got = arrow_map(mine, lambda it, w=w: _train(it, w.value, held.value, rate, batch), "slice int, n long, part binary")
        got = arrow_map(got.repartition(parts, "slice"), _average, "slice int, n long, part binary").toArrow()
        w.destroy()
        found = dict(zip(got.column("slice").to_pylist(), got.column("part").to_pylist()))
        if found:
            change = np.concatenate([np.frombuffer(found[s], np.float32) for s in range(SLICES)])
            model = Model(model.w + change)
    pairs = count_pairs(train, held, text)
    held.destroy()
    return model, pairs


def log_probabilities(h: np.ndarray, count: np.ndarray, book: Dictionary, model: Model, pairs: Pairs) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(log10 probability, training count, whether that is known here) of every token; a token whose count is not known yet lacks
    the logarithm of its count plus one, and one whose pair is not held those that ``Pairs.rest`` has for it."""
    place = book.find(h)
    ids = book.outputs(place)
    c = book.counts(place)
    told = (place >= 0) | book.full
    lp = model.score(ids, *history(ids, count)) / LN10
    rare = np.flatnonzero(ids < GROUPS)
    unigram = (c[rare] + 1.0) / np.maximum(book.mass[ids[rare]], 1.0)
    lp[rare] += np.log10(pairs(pair_keys(h, count, place, ids)[rare], unigram))
    return lp, c, told


def score_texts(docs: DataFrame, counts: Counts, model: Model, pairs: Pairs, text: str, doc_id: str, held: str) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of every row.

    Null texts count as empty: one end. Rows that repeat an id and its text come out once each. Long texts are
    worked on whole, in runs of rows of 2 MB or one row. Empty tables give empty results; without training rows every
    output is as likely as the smoothing makes it.
    """
    spark = docs.sparkSession
    tables = spark.sparkContext.broadcast((counts.book, model, pairs))
    frame = docs.select(F.col(doc_id).alias("d"), F.col(held).alias("held"), F.col(text).alias("t"))
    frame = frame.withColumn("r", F.xxhash64("d", F.coalesce("t", F.lit("")), F.col("d").isNull()))
    kind = dict(frame.dtypes)["d"]
    more_words, more_pairs = not counts.book.full, pairs.more

    def rarer_words(batches):
        """(row, word) of every token beyond the dictionary."""
        book = tables.value[0]
        for b in batches:
            for i, h, count in tokens(b.column(1)):
                rare = book.find(h) < 0
                row = np.repeat(np.arange(i, i + len(count)), count)[rare]
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(row)), pa.array(h[rare].view(np.int64))], names=["r", "w"])

    def rarer_pairs(batches):
        """(key as asked for, row) of every token whose weight is not held."""
        book, _, pairs = tables.value
        for b in batches:
            for i, h, count in tokens(b.column(1)):
                place = book.find(h)
                ids = book.outputs(place)
                key = pair_keys(h, count, place, ids)
                at = np.flatnonzero(ids < GROUPS)
                at = at[pairs.missing(key[at])]
                row = np.repeat(np.arange(i, i + len(count)), count)[at]
                yield pa.RecordBatch.from_arrays([pa.array(((key[at] >> 18) << 19) | (1 << 18) | (key[at] & LAST)), b.column(0).take(pa.array(row))], names=["s", "v"])

    def head(batches):
        book, model, pairs = tables.value
        for b in batches:
            n, known, logs, own = [], [], [], []
            for _, h, count in tokens(b.column(2)):
                lp, c, _ = log_probabilities(h, count, book, model, pairs)
                at = np.cumsum(count) - count
                n.append(count)
                known.append(np.add.reduceat((c > 0).astype(np.int64), at))
                logs.append(np.add.reduceat(np.log10(c + 1.0), at))
                own.append(np.add.reduceat(lp, at))
            cols = [np.concatenate(x) if x else np.zeros(0) for x in (n, known, logs, own)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(3), *[pa.array(x.astype(t)) for x, t in zip(cols, (np.int64, np.int64, float, float))]], names=["d", "held", "r", "n", "known", "logs", "own"])

    all_ = arrow_map(frame, head, f"d {kind}, held boolean, r long, n long, known long, logs double, own double")
    found = []
    if more_words:
        words = arrow_map(frame.select("r", "t"), rarer_words, "r long, w long").join(counts.table.hint("merge"), "w")
        log = F.log10(F.col("c") + 1.0)
        found.append(words.select("r", F.lit(1).alias("mk"), log.alias("ml"), log.alias("mv")))
    if more_pairs:
        counted = pairs.rest.select((F.shiftleft(F.shiftright("key", 18), 19).bitwiseOR(F.col("key").bitwiseAND(F.lit(LAST)))).alias("s"), F.col("n").alias("v"))
        both = counted.union(arrow_map(frame.select("r", "t"), rarer_pairs, "s long, v long")).repartition(F.shiftright("s", 19)).sortWithinPartitions("s")
        logs = settle(arrow_map(both, lambda it: _weights_of_rest(it, tables.value[0], tables.value[2]), "r long, mv double").groupBy("r").agg(F.sum("mv").alias("mv")))
        del counted, both
        release(spark)
        found.append(logs.select("r", F.lit(0).alias("mk"), F.lit(0.0).alias("ml"), "mv"))
    if found:
        sums = (found[0] if len(found) == 1 else found[0].union(found[1])).groupBy("r").agg(*[F.sum(c).alias(c) for c in ("mk", "ml", "mv")])
        times = frame.groupBy("r").agg(F.count("*").alias("times")).where("times > 1")  # repeated rows share what was found
        all_ = all_.join(sums.hint("merge"), "r", "left").join(times.hint("merge"), "r", "left")
    else:
        all_ = all_.select("*", *[F.lit(None).cast("double").alias(c) for c in ("mk", "ml", "mv", "times")])
    share = F.coalesce("times", F.lit(1))
    extra = lambda c: F.coalesce(F.col(c) / share, F.lit(0.0))
    return all_.select(
        F.col("d").alias(doc_id), F.col("held").alias("held_out"), F.col("n").alias("n_tokens"),
        (F.col("known") + extra("mk").cast("long")).cast("long").alias("n_known"),
        F.lit(counts.n).cast("long").alias("train_tokens"),
        (F.col("logs") + extra("ml") - F.col("n") * float(np.log10(counts.n + counts.v + 1))).alias("base_score"),
        (F.col("own") + extra("mv")).alias("score"),
    )


def lm_scores(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """The contract's query: rows whose id hash modulo 7 is 2 are held out (a null id is not). Nulls, repeats and empty tables as in
    ``score_texts``."""
    docs = docs.select(doc_id, text, F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 7 == 2, F.lit(False)).alias("held"))
    train = docs.where(~F.col("held"))
    counts = Counts(train, text)
    return score_texts(docs, counts, *train_model(train, counts, text, doc_id), text, doc_id, "held")
