"""Toxicity by nearest labelled examples under exact TF-IDF cosine.

Labelled rows (a bounded, hashed sample: ``examples``) give the inverse document frequencies and the
indexed examples.  All their words are terms.  A term's
weight grows with what its counts among toxic and clean examples differ beyond chance (likelihood
ratio); near copies of one text count once there.  Every text's k most similar examples are found exactly in a
block-max inverted index, vote with weights by similarity, and the vote is calibrated on
leave-one-out votes of the examples themselves.
"""

from __future__ import annotations

import copy
import hashlib
import itertools
import math
import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import forget, give_back, let_go, reach_workers, staged
from .shingles import shingle_hashes

NO_WORD = re.compile(r"[^\w ]+")
#: A space for every ASCII character that is in no word.
PARTED = bytes(b if b >= 128 or chr(b).isalnum() else 32 for b in range(256))


def words_apart(text: str | None) -> bytes:
    """The words (``\\w+``) of a text in lower case, spaces between; an underscore parts words."""
    lower = (text or "").lower()
    out = lower.encode("utf-8", "surrogatepass").translate(PARTED)
    if lower.isascii():
        return out
    apart = out.decode("utf-8", "surrogatepass")
    return out if apart.replace(" ", "").isalnum() else NO_WORD.sub(" ", apart).encode()


def terms_of(text: str | None) -> list[bytes]:
    return words_apart(text).split()


def likelihood_ratio(a: int, b: int, n1: int, n0: int) -> float:
    """2 ln of the ratio for a of n1 toxic and b of n0 clean texts holding a word."""
    out = 0.0
    total = n1 + n0
    for seen, rows, cols in ((a, n1, a + b), (b, n0, a + b), (n1 - a, n1, total - a - b), (n0 - b, n0, total - a - b)):
        if seen:
            out += seen * math.log(seen * total / (rows * cols))
    return 2 * out


def word_hashes(words) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words, itertools.repeat(42)), np.uint64, len(words))


class Vocabulary:
    """Terms by 64-bit hashes of their words, in order, each with its weight: 16 bytes a term, whatever the words."""

    #: Texts are looked up together until they have so many characters.
    TOGETHER = 1 << 20

    def __init__(self, hashes: np.ndarray, weight: np.ndarray):
        order = np.argsort(hashes, kind="stable")
        self.hashes, self.weight = hashes[order], weight[order]

    def numbers(self, words: list[bytes]) -> np.ndarray:
        """Term numbers of distinct words, -1 for unknown ones."""
        if not len(self.hashes):
            return np.full(len(words), -1, np.int64)
        h = word_hashes(words)
        order = np.argsort(h)  # neighbours in the table are searched one after the other
        h, at = h[order], np.empty(len(words), np.int64)
        near = np.minimum(np.searchsorted(self.hashes, h), len(self.hashes) - 1)
        at[order] = np.where(self.hashes[near] == h, near, -1)
        return at

    def vector(self, text: str | None) -> tuple[np.ndarray, np.ndarray]:
        """Term numbers in order and weights of unit norm; empty where no word is known."""
        return self._some([text])[0]

    def vectors(self, texts: list[str | None]) -> list[tuple[np.ndarray, np.ndarray]]:
        """``vector`` of each text."""
        out, lo, size = [], 0, 0
        for i, text in enumerate(texts):
            size += len(text or "")
            if size >= self.TOGETHER or i + 1 == len(texts):
                out += self._some(texts[lo : i + 1])
                lo, size = i + 1, 0
        return out

    def _some(self, texts: list[str | None]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Every word is hashed and looked up once, however many of the texts hold it."""
        apart = [words_apart(t) for t in texts]
        letters = np.frombuffer(b" ".join([b"", *apart, b""]), np.uint8)
        inside = letters != 32
        start, end = np.flatnonzero(inside[1:] > inside[:-1]) + 1, np.flatnonzero(inside[1:] < inside[:-1]) + 1
        of = np.searchsorted(np.cumsum([len(x) + 1 for x in apart]), start, side="right")
        ends = np.concatenate([[0], np.cumsum(end - start)])
        number = pa.Array.from_buffers(pa.large_binary(), len(start), [None, pa.py_buffer(ends), pa.py_buffer(letters[inside])]).dictionary_encode().indices.to_numpy()
        first = np.unique(number, return_index=True)[1]
        whole = letters.tobytes()
        words = list(map(whole.__getitem__, map(slice, start[first].tolist(), end[first].tolist())))
        terms = self.numbers(words)[number]
        width = len(self.hashes) + 1
        keys, tf = np.unique((of * width + terms)[terms >= 0], return_counts=True)
        ends = np.searchsorted(keys, np.arange(len(texts) + 1) * width)
        terms = (keys % width).astype(np.int32)
        raw = (1 + np.log(tf)) * self.weight[terms]
        out = []
        for a, b in itertools.pairwise(ends.tolist()):
            mine = raw[a:b]
            out.append((terms[a:b].copy(), mine / (math.sqrt(float(mine @ mine)) or 1.0)))
        return out


class BlockMaxIndex:
    """Examples by term: the commonest terms as a matrix in blocks of similar examples, each with its
    greatest weights; the others as postings.  Blocks are alike (of one language, say), so most can't hold a near example."""

    def __init__(self, vectors: list, block: int = 128, common: int = 512):
        self.block, self.common, self.size = block, common, len(vectors)
        self.start = np.concatenate([[0], np.cumsum([len(t) for t, _ in vectors])]).astype(np.int64)
        self.terms = np.concatenate([np.zeros(0, np.int32), *(np.asarray(t, np.int32) for t, _ in vectors)])
        self.weights = np.concatenate([np.zeros(0), *(np.asarray(w, float) for _, w in vectors)])
        self.query = None

    def __getstate__(self):
        return {k: self.__dict__[k] for k in ("block", "common", "size", "start", "terms", "weights")}

    def __setstate__(self, state):
        self.__dict__ |= state
        self.query = None

    def _build(self) -> None:
        """What searches need; made where the first one runs."""
        rows = np.repeat(np.arange(self.size, dtype=np.int32), np.diff(self.start))
        self.width = int(self.terms.max()) + 1 if len(self.terms) else 0
        count = np.bincount(self.terms, minlength=self.width)
        most = np.sort(np.argsort(-count, kind="stable")[: self.common])
        self.place = np.full(self.width, -1, np.int32)
        self.place[most] = np.arange(len(most))
        at = self.place[self.terms]
        self.matrix = np.zeros((self.size, len(most)), np.float32)
        self._fill(rows, at, np.arange(self.size, dtype=np.int32))
        self.original = alike(self.matrix, self.block)
        self.spot = np.empty(self.size, np.int32)
        self.spot[self.original] = np.arange(self.size, dtype=np.int32)
        self.matrix[:] = 0  # filled again in the new order: no second matrix
        self._fill(rows, at, self.spot)
        self.edges = list(range(0, self.size, self.block))
        self.greatest = np.maximum.reduceat(self.matrix, self.edges, axis=0) if self.size else self.matrix
        length = np.sqrt(np.einsum("ij,ij->i", self.matrix, self.matrix))
        self.longest = np.maximum.reduceat(length, self.edges) if self.size else length
        # Every worker of a machine builds at the same time, so postings are sorted a range of terms at a time.
        self.post_start = np.concatenate([[0], np.cumsum(np.where(self.place < 0, count, 0))]).astype(np.int64)
        total = int(self.post_start[-1])
        self.post_row, self.post_weight = np.empty(total, np.uint16 if self.size <= 1 << 16 else np.int32), np.empty(total, np.float32)
        cuts = [*np.searchsorted(self.post_start, np.arange(0, total, 1 << 19)).tolist(), self.width]
        for lo, hi in zip(cuts, cuts[1:]):
            rest = np.flatnonzero((self.terms >= lo) & (self.terms < hi) & (at < 0))
            rest = rest[np.argsort(self.terms[rest], kind="stable")]
            here = slice(self.post_start[lo], self.post_start[hi])
            self.post_row[here], self.post_weight[here] = self.spot[rows[rest]], self.weights[rest]
        del rows, at
        self.parts = list(range(0, self.size, max(1, min(64, self.size // 256))))
        self.query = np.zeros(self.width)
        give_back()

    def _fill(self, rows: np.ndarray, at: np.ndarray, spot: np.ndarray, step: int = 1 << 18) -> None:
        """The common terms' weights in the matrix, each example in its spot; a part at a time."""
        for lo in range(0, len(at), step):
            some = np.flatnonzero(at[lo : lo + step] >= 0) + lo
            self.matrix[spot[rows[some]], at[some]] = self.weights[some]

    def vector(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        at = slice(self.start[i], self.start[i + 1])
        return self.terms[at], self.weights[at]

    def _least(self, score: np.ndarray, k: int) -> np.ndarray:
        """A bound below each row's k-th best score: the k-th best of the bests of small parts."""
        most = np.maximum.reduceat(score, self.parts, axis=1)
        if most.shape[1] < k:
            return np.full(len(score), -1.0)
        return np.partition(most, most.shape[1] - k, axis=1)[:, most.shape[1] - k]

    def _open(self, score: np.ndarray, dense: np.ndarray, blocks, queries) -> None:
        """Add what the common terms say of the examples of blocks, for the queries that need it."""
        for b in np.unique(blocks):
            need, e = queries(b), self.edges[b]
            if len(need):
                score[need, e : e + self.block] += dense[need] @ self.matrix[e : e + self.block].T

    def nearest(self, terms, weights, k: int, skip=frozenset()) -> list[tuple[float, int]]:
        """The k highest cosines (similarity, example), ties to the lower number."""
        return self.nearest_of([(terms, weights)], k, [skip])[0]

    def nearest_of(self, queries: list, k: int, skips: list) -> list[list[tuple[float, int]]]:
        """``nearest`` of each query.  Rounded scores choose candidates with some slack, full vectors decide;
        blocks that can't reach the k-th best score by postings alone are not opened."""
        if self.query is None:
            self._build()
        if not self.size or not self.width:
            return [[] for _ in queries]
        queries = [(np.asarray(t, np.int64), np.asarray(w, float)) for t, w in queries]
        queries = [(t[t < self.width], w[t < self.width]) for t, w in queries]
        n, slack = len(queries), 1e-5
        of = np.repeat(np.arange(n), [len(t) for t, _ in queries])
        terms, weights = (np.concatenate(x) for x in zip(*queries))
        place = self.place[terms]
        dense = np.zeros((n, self.matrix.shape[1]), np.float32)
        dense[of[place >= 0], place[place >= 0]] = weights[place >= 0]
        rare, whose, by = terms[place < 0], of[place < 0], weights[place < 0].astype(np.float32)
        lengths = self.post_start[rare + 1] - self.post_start[rare]
        score = np.empty((n, self.size), np.float32)
        starts, ends = self.post_start[rare].tolist(), self.post_start[rare + 1].tolist()
        part = np.searchsorted(whose, np.arange(n + 1)).tolist()
        for i, (lo, hi) in enumerate(itertools.pairwise(part)):  # one query at a time: its postings are many
            if lo == hi:
                score[i] = 0
                continue
            lists = list(map(slice, starts[lo:hi], ends[lo:hi]))
            row, weight = pieces(self.post_row, lists), pieces(self.post_weight, lists)
            score[i] = np.bincount(row, weight * np.repeat(by[lo:hi], lengths[lo:hi]), self.size)
        for i, skip in enumerate(skips):
            if skip:
                score[i, self.spot[list(skip)]] = -2.0
        bound = np.maximum.reduceat(score, self.edges, axis=1)
        bound += np.minimum(dense @ self.greatest.T, np.sqrt((dense * dense).sum(axis=1))[:, None] * self.longest)
        # The most promising block first: its k-th best score closes most others.
        best = bound.argmax(axis=1)
        floor = self._least(score, k)
        self._open(score, dense, best, lambda b: np.flatnonzero(best == b))
        for b in np.unique(best):
            e = self.edges[b]
            mine, width = np.flatnonzero(best == b), min(self.block, self.size - e)
            if width >= k:
                floor[mine] = np.maximum(floor[mine], np.partition(score[mine, e : e + width], width - k, axis=1)[:, width - k])
        bound[np.arange(n), best] = -np.inf
        self._open(score, dense, range(len(self.edges)), lambda b: np.flatnonzero(bound[:, b] >= floor - slack))
        least = np.maximum(self._least(score, k), floor)
        out = []
        for i, (t, w) in enumerate(queries):
            found = np.flatnonzero(score[i] >= max(least[i], 0.0) - slack)
            if len(found) > k:
                found = found[score[i, found] >= np.partition(score[i, found], len(found) - k)[len(found) - k] - slack]
            if least[i] <= slack:
                found = found[score[i, found] > 0]
            found = np.sort(self.original[found])
            if skips[i]:
                found = found[~np.isin(found, list(skips[i]))]
            if not len(found):
                out.append([])
                continue
            size = self.start[found + 1] - self.start[found]
            lists = list(map(slice, self.start[found].tolist(), self.start[found + 1].tolist()))
            self.query[t] = w
            exact = np.add.reduceat(self.query[pieces(self.terms, lists)] * pieces(self.weights, lists), np.cumsum(size) - size)
            self.query[t] = 0.0
            best = [(round(float(s), 12), int(f)) for s, f in zip(exact, found) if s > 0]
            out.append(sorted(best, key=lambda x: (-x[0], x[1]))[:k])
        return out


def pieces(x: np.ndarray, lists: list[slice]) -> np.ndarray:
    """Slices of an array, joined: copied whole, where an index would take each element by itself."""
    joined = b"".join(map(memoryview(x).__getitem__, lists))
    return np.frombuffer(joined, x.dtype) if joined else x[:0]


def alike(rows: np.ndarray, block: int) -> np.ndarray:
    """An order of rows in which every ``block`` of them are similar: halves along the direction of most variance, again and again."""
    done, todo = [], [np.arange(len(rows))]
    while todo:
        some = todo.pop()
        if len(some) <= block:
            done.append(some)
            continue
        x = rows if len(some) == len(rows) else rows[some]
        mean = x.mean(axis=0)
        v = np.random.default_rng(7).standard_normal(x.shape[1]).astype(np.float32)
        for _ in range(8):
            along = x @ v - float(mean @ v)
            v = x.T @ along - mean * along.sum()
            v /= np.sqrt(float(v @ v)) or 1.0
        order = np.argsort(x @ v, kind="stable")
        half = block * -(-len(some) // (2 * block))
        todo += [some[order[half:]], some[order[:half]]]
    return np.concatenate(done) if done else np.zeros(0, np.int64)


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Non-decreasing fit by pooling neighbours that break the order."""
    order = np.argsort(x, kind="stable")
    level: list[list[float]] = []
    for v, t in zip(x[order], y[order]):
        level.append([float(t), 1.0, float(v)])
        while len(level) > 1 and level[-2][0] / level[-2][1] >= level[-1][0] / level[-1][1]:
            a = level.pop()
            level[-1] = [level[-1][0] + a[0], level[-1][1] + a[1], a[2]]
    # One pseudo-count each way keeps every value inside (0, 1).
    return np.array([v for _, _, v in level]), np.array([(s + 0.05) / (n + 0.1) for s, n, _ in level])


class Scorer:
    """What a machine needs to score texts: all parts are bounded by the examples and their words."""

    #: Texts searched together.
    AT_ONCE = 256

    def __init__(self, vocabulary: Vocabulary, ids: list[int], labels: list[int], vectors: list, copies: list[int], k: int):
        full = [i for i, (t, _) in enumerate(vectors) if len(t)]
        bare = [i for i, (t, _) in enumerate(vectors) if not len(t)]
        self.vocabulary, self.k = vocabulary, k
        self.prior = (sum(labels) + 0.5) / (len(labels) + 1) if labels else 0.0
        self.base = (sum(labels[i] for i in bare) + self.prior) / (len(bare) + 1)
        self.ids = [ids[i] for i in full]
        self.labels = np.array([labels[i] for i in full], float)
        self.index = BlockMaxIndex([vectors[i] for i in full])
        of: dict[int, list[int]] = {}
        for n, i in enumerate(full):
            of.setdefault(copies[i], []).append(n)
        self.same = [of[copies[i]] for i in full]
        self.at, self.to = np.zeros(0), np.zeros(0)
        self.seen: dict = {}

    def votes(self, numbers: list[int]) -> list[float]:
        """Votes on examples by the others, near copies left out."""
        out = []
        for j in range(0, len(numbers), self.AT_ONCE):
            some = numbers[j : j + self.AT_ONCE]
            out += [self.vote(best) for best in self.index.nearest_of([self.index.vector(i) for i in some], self.k, [self.same[i] for i in some])]
        return out

    def calibrate(self, votes: list[float]) -> None:
        if votes:
            self.at, self.to = isotonic(np.array(votes), self.labels)
        self.same = None

    def vote(self, best: list[tuple[float, int]]) -> float:
        weight = sum(s * s for s, _ in best)
        return (sum(s * s * self.labels[i] for s, i in best) + 0.5 * self.prior) / (weight + 0.5)

    def score(self, texts: list[str | None]) -> list[tuple[float, list[tuple[int, float, int]]]]:
        """Score and nearest examples of each text."""
        if not len(self.at):
            return [(self.base, []) for _ in texts]
        out = []
        for j in range(0, len(texts), self.AT_ONCE):
            some = texts[j : j + self.AT_ONCE]
            keys = [hashlib.blake2b((t or "").encode("utf-8", "surrogatepass"), digest_size=16).digest() for t in some]
            if len(self.seen) > 20_000:
                self.seen.clear()
            new = {key: t for key, t in dict(zip(keys, some)).items() if key not in self.seen}
            if new:
                new = dict(zip(new, self.vocabulary.vectors(list(new.values()))))
                for key, best in zip(new, self.index.nearest_of(list(new.values()), self.k, [frozenset()] * len(new))):
                    if not best:
                        self.seen[key] = (self.base, [])
                        continue
                    vote = self.vote(best)
                    calibrated = self.to[min(int(np.searchsorted(self.at, vote)), len(self.to) - 1)]
                    self.seen[key] = (float(0.95 * calibrated + 0.05 * vote), [(self.ids[i], s, int(self.labels[i])) for s, i in best[:3]])
            out += [self.seen[key] for key in keys]
        return out


def one_thread_each(spark) -> None:
    """Tasks share a machine's cores already; threads of the matrix product would only wait for them."""
    spark.sparkContext.environment["OPENBLAS_NUM_THREADS"] = "1"


def held_out(doc_id: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 5 == 0, F.lit(False))


def fit(docs: DataFrame, labels: DataFrame, examples: int = 16_384, k: int = 15) -> Scorer:
    """Learn from labelled rows that are not held out.

    ``examples`` bounds the labelled rows used; all words of their whole texts are used.  Empty tables, texts and labels give
    a scorer that knows nothing: every score is then the rate of toxic labels, or 0.  Null labels and ids are left out; of several labels of a doc_id the greatest counts.
    """
    reach_workers(docs.sparkSession)
    one_thread_each(docs.sparkSession)
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(examples)
    # At most ``examples`` ids and labels are broadcast, so no text moves.
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")

    def copy_of(text: str | None) -> int:
        h = shingle_hashes(text)
        return int(h[:1].view(np.int64)[0]) if len(h) else 0

    def spell(batches):
        let_go()
        for batch in batches:
            rows = [(copy_of(t), y, word_hashes(set(terms_of(t))).view(np.int64)) for t, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())]
            yield pa.record_batch([pa.array([c for c, _, _ in rows], pa.int64()), pa.array([y for _, y, _ in rows], pa.int32()), pa.array([w for _, _, w in rows], pa.list_(pa.int64()))], ["copy", "toxic", "words"])

    spelt = staged(sample.select("text", "toxic").mapInArrow(spell, "copy long, toxic int, words array<long>"), "examples")
    sizes = {r["toxic"]: r["n"] for r in spelt.select("copy", "toxic").distinct().groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    n1, n0 = sum(n for y, n in sizes.items() if y), sizes.get(0, 0)
    n = float(n1 + n0)
    counts = spelt.select("copy", "toxic", F.explode("words").alias("word")).distinct().groupBy("word").agg(F.sum(F.when(F.col("toxic") > 0, 1).otherwise(0)).alias("a"), F.sum(F.when(F.col("toxic") > 0, 0).otherwise(1)).alias("b"))
    a, b = F.col("a").cast("double"), F.col("b").cast("double")
    term = lambda x, rows, cols: F.when(x > 0, x * F.log(x * n / (rows * cols))).otherwise(0.0)
    ratio = 2 * (term(a, F.lit(float(n1)), a + b) + term(b, F.lit(float(n0)), a + b) + term(n1 - a, F.lit(float(n1)), n - a - b) + term(n0 - b, F.lit(float(n0)), n - a - b)) if n1 and n0 else F.lit(0.0)
    # One hash and weight for each word of the examples, whose number is bounded.
    table = counts.select("word", (F.log(1 + n / (a + b)) * (1 + F.greatest(ratio, F.lit(0.0)))).alias("weight")).toArrow()
    vocabulary = Vocabulary(table.column(0).to_numpy().view(np.uint64), table.column(1).to_numpy())
    del table
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary)

    def vectors(batches):
        let_go()
        for batch in batches:
            texts = batch.column(1).to_pylist()
            got, copies = shared.value.vectors(texts), [copy_of(t) for t in texts]
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array([t for t, _ in got], pa.list_(pa.int32())), pa.array([w for _, w in got], pa.list_(pa.float64())), pa.array(copies, pa.int64())], ["doc_id", "toxic", "terms", "weights", "copy"])

    got = sample.select("doc_id", "text", "toxic").mapInArrow(vectors, "doc_id long, toxic int, terms array<int>, weights array<double>, copy long").toArrow()
    rows = [(i, y, t.values.to_numpy(), w.values.to_numpy(), c) for i, y, t, w, c in zip(got.column("doc_id").to_pylist(), got.column("toxic").to_pylist(), got.column("terms"), got.column("weights"), got.column("copy").to_pylist())]
    del got
    rows.sort(key=lambda r: (r[0], r[2].tobytes(), r[3].tobytes()))
    forget(spelt)
    shared.unpersist()
    scorer = Scorer(vocabulary, [r[0] for r in rows], [int(r[1] > 0) for r in rows], [(r[2], r[3]) for r in rows], [r[4] for r in rows], k)
    del rows
    wordless = copy.copy(scorer)
    wordless.vocabulary = None
    searched = docs.sparkSession.sparkContext.broadcast(wordless)

    def vote(batches):
        let_go()
        for batch in batches:
            yield pa.record_batch([batch.column(0), pa.array(searched.value.votes(batch.column(0).to_pylist()), pa.float64())], ["id", "vote"])

    n = len(scorer.ids)
    votes = docs.sparkSession.range(0, n, 1, max(1, n // 512)).mapInArrow(vote, "id long, vote double").toArrow().sort_by("id")
    searched.unpersist()
    scorer.calibrate(votes.column("vote").to_pylist())
    return scorer


def score_documents(docs: DataFrame, scorer: Scorer) -> DataFrame:
    """doc_id, score, predicted and evidence (nearest examples with similarity and label) of every row, from its text alone.

    Null and empty texts and texts without a known word get the rate of textless examples, or of all; with
    no labels at all every score is 0.  Null and repeated doc_ids are scored like others.
    """
    reach_workers(docs.sparkSession)
    one_thread_each(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(scorer)

    def score(batches):
        let_go()
        s = shared.value
        for batch in batches:
            got = s.score(batch.column(1).to_pylist())
            value = np.clip([x for x, _ in got], 0.0, 1.0).astype(float)
            proof = [[{"doc_id": i, "similarity": sim, "toxic": y} for i, sim, y in e] for _, e in got]
            kind = pa.list_(pa.struct([("doc_id", pa.int64()), ("similarity", pa.float64()), ("toxic", pa.int32())]))
            yield pa.record_batch([batch.column(0), pa.array(value), pa.array((value >= 0.5).astype(np.int32)), pa.array(proof, kind)], ["doc_id", "score", "predicted", "evidence"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(score, "doc_id long, score double, predicted int, evidence array<struct<doc_id: long, similarity: double, toxic: int>>")


def without_toxic(docs: DataFrame, scorer: Scorer, threshold: float = 0.5) -> DataFrame:
    """The rows of docs, all columns as they are, whose text scores below the threshold.

    Null and empty texts score like textless examples and stay unless most of those are toxic; very long texts are scored
    whole; repeated rows all stay or all go; an empty table gives no rows; no column but ``text`` is read, whatever the others are called.
    """
    reach_workers(docs.sparkSession)
    one_thread_each(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(scorer)
    at = docs.columns.index("text")

    def keep(batches):
        let_go()
        for batch in batches:
            yield batch.filter(pa.array([x < threshold for x, _ in shared.value.score(batch.column(at).to_pylist())], pa.bool_()))

    return docs.mapInArrow(keep, docs.schema)
