"""Benchmark decontamination with a block-max BM25 index of the test items.

The test items form an inverted index with BM25 impacts; training passages are its
queries. Each item has its own threshold: the least score that a passage can have
when it holds the share ``OVERLAP`` of the item's five-word shingles, that is the
item's score against itself less its best-weighted words, as many as may be
missing. Impacts are divided by it, so every item is wanted from a score of 1 and
no leaking passage can fall below.

Retrieval of all items from 1 up is block-max WAND. The best impact of each term and
the best impacts of a term in each block of items first rule out passages, many at a
time. A passage that is left walks its terms' postings item by item: cursors are kept in
the order of their items, the first at which the terms' bounds add up to 1 is the pivot,
a pivot whose block bounds fall short moves the cursors past the block, and only a pivot
that all cursors before it have reached is scored. Then the shingles of question (all sentences but the last) and answer (the last one) are
compared: a document leaks an item if one passage has the share ``OVERLAP`` of the
shingles of both, or of the whole item.

Words are split at white space, lower-cased, and stripped of characters at their
ends that are neither letters nor digits. Passages are windows of two strides; a
stride is as long as the longest item, 64 words at least.

The index of a part of the items is broadcast; parts are cut by a measured size, so
no broadcast grows with the benchmark. Impacts use the statistics of their part,
which does not change the result.

Nulls: a null text has no words and neither leaks nor is leaked. Repeated documents
are judged each; repeated item ids count as one item in the result. A very long text is
searched passage by passage, with all its passages. Empty tables give empty results;
further columns are dropped (``drop_leaking`` keeps them).
"""

from __future__ import annotations

import math
from array import array
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.llm.words import byte_slices

WIDTH, OVERLAP = 5, 0.8
K1, B = 1.2, 0.75
MIN_STRIDE = 64
ITEM_BLOCK = 8
#: Bytes of item texts in one broadcast index.
PART_BYTES = 32 << 20
#: Bytes of text that are searched at once, and words whose terms a worker keeps.
SLICE_BYTES = 2 << 20
#: Pairs of a passage and a block of items whose bounds are added up at once.
CELLS = 1 << 22
MEMO = 200_000
#: Bounds are compared with a little less than 1: they are added up in another order than scores.
NEARLY = 1 - 1e-9
RESULT = "key {kind}, item_id bigint, question_overlap double, answer_overlap double, overlap double, score double"


def normal(word: str) -> str:
    """Lower case, without other characters than letters and digits at the ends."""
    word = word.lower()
    if word.isalnum():
        return word
    a, b = 0, len(word)
    while a < b and not word[a].isalnum():
        a += 1
    while b > a and not word[b - 1].isalnum():
        b -= 1
    return word[a:b]


def normal_words(text: str) -> list[str]:
    return [w for w in map(normal, text.split()) if w]


def shingles(words: list[str], width: int = WIDTH) -> list[tuple[str, ...]]:
    if not words:
        return []
    return [tuple(words[k : k + width]) for k in range(max(1, len(words) - width + 1))]


def question_and_answer(text: str) -> tuple[list[str], list[str]]:
    """Normal words of all sentences but the last, and of the last; one sentence is both."""
    raw = text.split()
    ends = [k for k, w in enumerate(raw[:-1]) if w.rstrip("\"')")[-1:] in (".", "?", "!")]
    cut = ends[-1] + 1 if ends else 0
    answer = normal_words(" ".join(raw[cut:]))
    question = normal_words(" ".join(raw[:cut])) if cut else answer
    return (question or answer), (answer or question)


class Item:
    __slots__ = ("item_id", "words", "question", "answer", "whole")

    def __init__(self, item_id: int, text: str):
        self.item_id, self.words = item_id, normal_words(text)
        question, answer = question_and_answer(text)
        self.question, self.answer, self.whole = shingles(question), shingles(answer), shingles(self.words)

    def overlaps(self, found: set[tuple[str, ...]]) -> tuple[float, float, float]:
        share = lambda own: sum(s in found for s in own) / len(own)
        return share(self.question), share(self.answer), share(self.whole)

    def widths(self) -> set[int]:
        return {len(own[0]) for own in (self.question, self.answer, self.whole)}


class BlockMaxIndex:
    """Postings of scaled impacts: by term, and inside a term by block of items."""

    def __init__(self, items: list[tuple[int, str]]):
        self.items = [x for x in (Item(i, t) for i, t in items) if x.words]
        n = len(self.items)
        counts = [Counter(x.words) for x in self.items]
        in_items = Counter(t for c in counts for t in c)
        mean = sum(len(x.words) for x in self.items) / max(1, n)
        self.terms: dict[str, int] = {}
        postings: list[tuple[int, int, float]] = []
        for at, (item, count) in enumerate(zip(self.items, counts, strict=True)):
            norm = K1 * (1 - B + B * len(item.words) / mean)
            impact = {t: math.log(1 + (n - in_items[t] + 0.5) / (in_items[t] + 0.5)) * c * (K1 + 1) / (c + norm) for t, c in count.items()}
            spare = int((1 - OVERLAP) * len(item.words) + 1e-9)
            best = sorted(impact.values(), reverse=True)
            need = sum(best[spare:]) * (1 - 1e-9)
            if need <= 0:  # every word may be missing: any shared word is a candidate
                need = min(best)
            for t, w in impact.items():
                postings.append((self.terms.setdefault(t, len(self.terms)), at, w / need))
        postings.sort()
        term = np.array([p[0] for p in postings], dtype=np.int64)
        self.item = np.array([p[1] for p in postings], dtype=np.int64)
        self.weight = np.array([p[2] for p in postings])
        self.first = np.searchsorted(term, np.arange(len(self.terms) + 1))
        self.bound = np.maximum.reduceat(self.weight, self.first[:-1]) if len(postings) else np.zeros(0)
        # one entry for each (term, block of items): the block's best impact
        block = term * (n // ITEM_BLOCK + 1) + self.item // ITEM_BLOCK
        starts = np.flatnonzero(np.append(True, block[1:] != block[:-1])) if len(block) else np.zeros(0, dtype=np.int64)
        self.block_bound = np.maximum.reduceat(self.weight, starts) if len(starts) else np.zeros(0)
        self.block_of = self.item[starts] // ITEM_BLOCK
        self.block_start = np.append(starts, len(block))
        self.block_first = np.searchsorted(term[starts], np.arange(len(self.terms) + 1))
        # the walk looks at one entry at a time, which plain arrays hand out faster
        plain = lambda x: array("d" if x.dtype.kind == "f" else "q", x.tobytes())
        self.walked = tuple(map(plain, (self.item, self.weight, self.first, self.bound, self.block_of, self.block_bound, self.block_first)))

    @staticmethod
    def _ranges(first: np.ndarray, terms: np.ndarray) -> np.ndarray:
        a, n = first[terms], first[terms + 1] - first[terms]
        return np.repeat(a - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(int(n.sum()))

    def search(self, passage: np.ndarray, term: np.ndarray, n: int) -> list[tuple[int, int, float]]:
        """(passage, item, score) of all scaled scores from 1 up; ``term`` are the distinct terms of ``passage``, sorted by passage."""
        blocks, out = len(self.items) // ITEM_BLOCK + 1, []
        alive = np.bincount(passage, self.bound[term], minlength=n) >= NEARLY
        keep = alive[passage]
        passage, term = passage[keep], term[keep]
        step = max(1, CELLS // blocks)
        for base in range(0, n, step):
            a, b = np.searchsorted(passage, [base, base + step])
            if a == b:
                continue
            own, terms = passage[a:b], term[a:b]
            at, of = self._ranges(self.block_first, terms), self.block_first[terms + 1] - self.block_first[terms]
            cell = np.repeat(own - base, of) * blocks + self.block_of[at]
            left = np.flatnonzero(np.bincount(cell, self.block_bound[at]) >= NEARLY) // blocks + base
            for p in np.unique(left).tolist():
                x, y = np.searchsorted(own, [p, p + 1])
                out += [(p, item, score) for item, score in self.walk(terms[x:y].tolist())]
        return out

    def walk(self, terms: list[int]) -> list[tuple[int, float]]:
        """(item, score) of all items from a score of 1 up, by pivots."""
        out = []
        items, weight, first, bound, block_of, block_bound, block_first = self.walked
        cursors = [[items[first[t]], first[t], t] for t in terms]  # item, place in the postings, term
        while cursors:
            cursors.sort()
            total, pivot = 0.0, None
            for pivot, (item, _, t) in enumerate(cursors):
                total += bound[t]
                if total >= NEARLY:
                    break
            else:
                return out
            while pivot + 1 < len(cursors) and cursors[pivot + 1][0] == item:
                pivot += 1
            block = item // ITEM_BLOCK
            total = 0.0
            for _, _, t in cursors[: pivot + 1]:
                b = block_first[t + 1]
                at = bisect_left(block_of, block, block_first[t], b)
                if at < b and block_of[at] == block:
                    total += block_bound[at]
            if total < NEARLY:
                goal = (block + 1) * ITEM_BLOCK
                if pivot + 1 < len(cursors):
                    goal = min(goal, cursors[pivot + 1][0])
            elif cursors[0][0] == item:
                score = 0.0  # added up one by one: sum() of floats rounds in another way
                for _, at, _ in cursors[: pivot + 1]:
                    score += weight[at]
                if score >= 1:
                    out.append((item, score))
                goal = item + 1
            else:
                goal = item
            for c in cursors[: pivot + 1]:
                if c[0] < goal:
                    end = first[c[2] + 1]
                    c[1] = bisect_left(items, goal, c[1], end)
                    c[0] = items[c[1]] if c[1] < end else -1
            cursors = [c for c in cursors if c[0] >= 0]
        return out


class TermMemo(dict):
    """Number of the term of each word as written, -1 for words that no item has."""

    def __init__(self, index: BlockMaxIndex):
        self.known = index.terms

    def __missing__(self, word: str) -> int:
        found = self[word] = self.known.get(normal(word), -1)
        return found


def leaks(texts: list[str | None], index: BlockMaxIndex, stride: int, memo: TermMemo) -> list[tuple[int, int, float, float, float, float]]:
    """(text, item id, overlap with question, answer and whole, score) of every item that a text leaks."""
    if len(memo) > MEMO:
        memo.clear()
    words = [t.split() if t else [] for t in texts]
    count = [len(x) // stride + 2 for x in words]  # the last segment of each text is empty
    base = np.append(0, np.cumsum(count))
    keys = []
    for k, x in enumerate(words):
        if x:
            ids = np.array(list(map(memo.__getitem__, x)), dtype=np.int64)
            at = np.flatnonzero(ids >= 0)
            keys.append((base[k] + at // stride) * len(index.terms) + ids[at])
    if not keys or not len(index.terms):
        return []
    pairs = np.unique(np.concatenate(keys))
    # a passage is a segment and the next one; where a text starts, the segment before is the last, empty one of the text before
    pairs = np.unique(np.concatenate([pairs, pairs - len(index.terms)]))
    pairs = pairs[pairs >= 0]
    hits = index.search(pairs // len(index.terms), pairs % len(index.terms), int(base[-1]))
    best: dict[tuple[int, int], tuple] = {}
    last, found = None, {}
    for s, i, score in hits:
        k = int(np.searchsorted(base, s, side="right")) - 1
        at = (s - int(base[k])) * stride
        if at >= len(words[k]) or at and at + stride >= len(words[k]):
            continue  # no passage, or the one before has all of it
        if s != last:
            last, found = s, {}
            own = [w for w in map(normal, words[k][at : at + 2 * stride]) if w]
        item = index.items[i]
        for width in item.widths() - found.keys():
            found[width] = {tuple(own[j : j + width]) for j in range(len(own) - width + 1)}
        q, a, whole = item.overlaps(set().union(*(found[w] for w in item.widths())))
        if whole >= OVERLAP or min(q, a) >= OVERLAP:
            row = (q, a, whole, score)
            best[k, item.item_id] = max(best.get((k, item.item_id), row), row)
    return [(k, i, *row) for (k, i), row in sorted(best.items(), key=lambda x: (x[0][0], x[0][1] is not None, x[0][1] or 0))]


def index_parts(items: DataFrame, item_key: str = "item_id", item_text: str = "text") -> Iterator[tuple[BlockMaxIndex, int]]:
    """Indexes of parts of the items, each over about PART_BYTES of text at most, and the stride that all share."""

    def lengths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in byte_slices(batches, 0, SLICE_BYTES):
            yield pa.RecordBatch.from_arrays([pa.array([len(t.split()) for t in batch.column(0).to_pylist()], pa.int64())], ["n"])

    own = items.where(F.col(item_text).isNotNull()).select(F.col(item_key).cast("bigint").alias("i"), F.col(item_text).alias("t")).distinct()
    longest = own.select("t").mapInArrow(lengths, "n bigint").agg(F.max("n")).first()[0]  # the words that passages are cut by
    parts = (own.agg(F.sum(F.octet_length("t"))).first()[0] or 0) // PART_BYTES + 1
    spread = F.xxhash64("i", F.when(F.col("i").isNull(), F.col("t")))
    for part in range(parts):
        rows = own.where(F.pmod(spread, F.lit(parts)) == part).orderBy("i", "t").collect()
        yield BlockMaxIndex([(r[0], r[1]) for r in rows]), max(MIN_STRIDE, longest or 0)


def find_leaks(docs: DataFrame, items: DataFrame, text: str = "text", key: str = "doc_id", item_key: str = "item_id", item_text: str = "text") -> DataFrame:
    """(key, item_id, question_overlap, answer_overlap, overlap, score) of each document and item that it leaks."""
    spark = docs.sparkSession
    of = docs.schema[key].dataType.simpleString()
    schema = RESULT.format(kind=of)
    out = None
    for part, stride in index_parts(items, item_key, item_text):
        index = spark.sparkContext.broadcast(part)

        def run(batches: Iterator[pa.RecordBatch], index=index, stride=stride) -> Iterator[pa.RecordBatch]:
            memo = TermMemo(index.value)
            for batch in byte_slices(batches, 1, SLICE_BYTES):
                found = leaks(batch.column(1).to_pylist(), index.value, stride, memo)
                if found:
                    at = pa.array([r[0] for r in found], pa.int64())
                    numbers = [pa.array([r[c] for r in found], pa.int64() if c == 1 else pa.float64()) for c in range(1, 6)]
                    yield pa.RecordBatch.from_arrays([batch.column(0).take(at), *numbers], ["key", "item_id", "question_overlap", "answer_overlap", "overlap", "score"])

        found = docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(run, schema)
        out = found if out is None else out.union(found)
    return out


def drop_leaking(docs: DataFrame, items: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """The rows of ``docs`` that leak no item."""
    names = docs.columns
    spark = docs.sparkSession
    at = names.index(text)
    for part, stride in index_parts(items):
        index = spark.sparkContext.broadcast(part)

        def run(batches: Iterator[pa.RecordBatch], index=index, stride=stride) -> Iterator[pa.RecordBatch]:
            memo = TermMemo(index.value)
            for batch in byte_slices(batches, at, SLICE_BYTES):
                bad = {r[0] for r in leaks(batch.column(at).to_pylist(), index.value, stride, memo)}
                yield batch.filter(pa.array([k not in bad for k in range(batch.num_rows)], pa.bool_()))

        docs = docs.mapInArrow(run, docs.schema)
    return docs


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pairs of a document and a benchmark item that it leaks."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    return find_leaks(docs, items).withColumnRenamed("key", "doc_id")
