"""Removal of repeated passages by recompression.

Words are named by hashes. Two rounds of recompression follow, each first naming
runs of equal symbols and then pairs: a fixed coin puts every symbol on the left or
right, and a left symbol merges with a right one after it. Names are hashes of what
they stand for, so they are the same in every document and on every executor without
an exchange. Every symbol also knows the words that its parse depends on; all
occurrences of those words have the symbol.

A window of 20 words is represented by that symbol, among those that depend on words
of the window alone, whose surroundings have the least name; equal windows have equal
representatives. Consecutive windows with the same representative form a unit (about
one for eight words). Units meet by the name of their representative's surroundings:

* a unit whose words are those of an earlier unit is a repeat as a whole;
* units that share a representative and differ are compared window by window;
* all others are unique, which is most of the text, and are not looked at again.

Equality of units and windows is verified on 128-bit hashes of all their words.

Before each exchange a task compares its own rows: repeats inside the task need no
exchange, and of units with one representative at most two are sent to meet those of
other tasks, while the rest is compared by window anyway. A passage that a third of
all documents share so sends a few rows from each task, whatever its frequency.

Units and representatives that are frequent in a slice are remembered for the slices after
it (about ``HOT`` of each), so a task sends a frequent passage once and not once a slice.

A document is known by its id and a turn: zero while no id comes with two texts, else a
hash of the text. A row without an id takes two hashes of its text in their place. So no
step gathers the rows of one id, and rows without an id are as many documents as texts.

Nulls: a null text has no words; rows without an id come before all others, in the order
of a hash of the text. Rows that repeat id and text are one document; texts with the same
id are ordered by a hash of the text. Texts of fewer than 20 words, alone or not, lose
nothing. A very long text is parsed by the task that holds its row. An empty table gives
an empty result. Further columns are dropped.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.llm.words import byte_slices

WINDOW = 20
ROUNDS = 2
#: Bytes of text that a task parses at once.
CHUNK_BYTES = 6 << 20
#: Added to the starts of rows without an id, which come first.
LOST = -(1 << 62)
#: Repeated units that a task remembers.
HOT = 100_000
NONE = np.uint64(0xFFFFFFFFFFFFFFFF)
MASK64 = (1 << 64) - 1


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit words whose every output bit depends on every input bit."""
    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return x ^ (x >> np.uint64(33))


def factors(seed: int, n: int) -> list[np.uint64]:
    return [np.uint64(xxhash.xxh64_intdigest(k.to_bytes(4, "little"), seed) | 1) for k in range(n)]


FACTORS = [factors(11, WINDOW), factors(12, WINDOW)]


def window_hash(words: np.ndarray, width: int, m: list[np.uint64]) -> np.ndarray:
    """Hash of the ``width`` words from each place on; the last places are meaningless."""
    out = words * m[0]
    for k in range(1, min(width, len(words))):
        out[: len(words) - k] += words[k:] * m[k]
    return mix(out)


class Chunk:
    """Words of some texts, one after the other, with a mark before, between and after them."""

    def __init__(self, texts: pa.Array):
        lists = pc.ascii_split_whitespace(pc.fill_null(texts.cast(pa.string()), ""))
        flat = lists.flatten()
        real = pc.not_equal(flat, "").to_numpy(zero_copy_only=False)
        ends = np.append(0, np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False)))
        size = np.append(0, np.cumsum(real))[ends]
        codes = flat.filter(pa.array(real)).dictionary_encode() if len(flat) else pa.array([], pa.string()).dictionary_encode()
        digest = [xxhash.xxh3_128_intdigest(w) for w in codes.dictionary.cast(pa.binary()).to_pylist()]
        table = np.array([[d & MASK64, d >> 64] for d in digest], dtype=np.uint64).reshape(-1, 2)
        at = codes.indices.to_numpy(zero_copy_only=False)
        self.n_texts = len(texts)
        self.counts = np.diff(size)
        #: Place of each text's first word.
        self.first = size[:-1] + np.arange(self.n_texts) + 1
        n = int(size[-1]) + self.n_texts + 1
        self.mark = np.zeros(n, dtype=bool)
        self.mark[np.append(self.first - 1, n - 1)] = True
        self.words = [np.zeros(n, dtype=np.uint64) for _ in range(2)]
        for k in range(2):
            self.words[k][~self.mark] = table[at, k]
        self.n = n

    def windows(self) -> np.ndarray:
        """Whether a window of words of one text starts at each place."""
        marks = np.append(0, np.cumsum(self.mark))
        ok = np.zeros(self.n, dtype=bool)
        if self.n >= WINDOW:
            ok[: self.n - WINDOW + 1] = marks[WINDOW:] == marks[: self.n + 1 - WINDOW]
        return ok

    def hashes(self) -> list[np.ndarray]:
        return [window_hash(w, WINDOW, m) for w, m in zip(self.words, FACTORS, strict=True)]

    def text_of(self, places: np.ndarray) -> np.ndarray:
        return np.searchsorted(self.first, places, side="right") - 1


def parse(chunk: Chunk, rounds: int = ROUNDS) -> tuple[np.ndarray, np.ndarray]:
    """(low, high) of the words that each symbol of the last round depends on."""
    start = np.arange(chunk.n)
    end, name, mark = start + 1, chunk.words[0], chunk.mark
    low, high = start, end  # before the first round a symbol is its word
    for _ in range(rounds):
        # runs: the symbols beside a run must be known to differ from it
        new = np.ones(len(name), dtype=bool)
        new[1:] = (name[1:] != name[:-1]) | mark[1:] | mark[:-1]
        head = np.flatnonzero(new)
        tail = np.append(head[1:], len(name)) - 1
        length = tail - head + 1
        low, high = low[np.maximum(head - 1, 0)], high[np.minimum(tail + 1, len(name) - 1)]
        base, mark = name[head], mark[head]
        name = np.where(length > 1, mix(base + np.uint64(0x9E3779B97F4A7C15) * length.astype(np.uint64)), base)
        start, end = start[head], end[tail]
        # pairs: the coin of a run is that of its symbol, which the run's own words decide
        left = (mix(base ^ np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(63)).astype(bool)
        merges = np.zeros(len(name), dtype=bool)
        merges[:-1] = left[:-1] & ~left[1:] & ~mark[:-1] & ~mark[1:]
        stays = np.ones(len(name), dtype=bool)
        stays[1:] = ~merges[:-1]
        at = np.flatnonzero(stays)
        last = at + merges[at]
        name = np.where(merges[at], mix(name[at] * np.uint64(3) + mix(name[last])), name[at])
        start, end, low, high, mark = start[at], end[last], low[at], high[last], mark[at]
    return low[~mark], high[~mark]


def units(chunk: Chunk) -> dict[str, np.ndarray]:
    """Units of a chunk: name of the representative's surroundings, two hashes, first window and number of windows."""
    ok, (h1, h2) = chunk.windows(), chunk.hashes()
    low, high = parse(chunk)
    fits = (high - low <= WINDOW) & (low >= 0)
    low, high = low[fits], high[fits]
    part = window_hash(chunk.words[0], 4, FACTORS[1])
    around = mix(part[low] + mix(part[np.maximum(high - 4, low)]) + (high - low).astype(np.uint64))
    bits = np.uint64(max(1, len(low)).bit_length())
    rank = (around >> bits << bits) | np.arange(len(low), dtype=np.uint64)
    best = np.full(chunk.n, NONE)
    room = WINDOW - (high - low)
    for k in range(int(room.max(initial=-1)) + 1):
        of = np.flatnonzero((room >= k) & (low >= k))
        at = low[of] - k
        best[at] = np.minimum(best[at], rank[of])
    chosen = np.where(best == NONE, np.int64(-1), (best & ((np.uint64(1) << bits) - np.uint64(1))).astype(np.int64))
    chosen[~ok] = -2
    opens = np.ones(chunk.n, dtype=bool)
    opens[1:] = (chosen[1:] != chosen[:-1]) | (chosen[1:] == -1)
    first = np.flatnonzero(opens)
    last = np.append(first[1:], chunk.n) - 1
    keep = chosen[first] != -2
    first, last = first[keep], last[keep]
    symbol = chosen[first]
    key = np.where(symbol >= 0, around[symbol] if len(around) else np.uint64(0), mix(h1[first]))
    size = (last - first + 1).astype(np.uint64)
    whole = [mix(h[first] + mix(h[last] + size)) for h in (h1, h2)]
    return {"key": key, "u1": whole[0], "u2": whole[1], "first": first, "n": last - first + 1}


# Rows of an exchange: 0 meets others, 1 is compared by window, 2 is a repeat.
MEETS, BY_WINDOW, REPEAT = 0, 1, 2
ROWS = "route bigint, u1 bigint, u2 bigint, doc bigint, turn bigint, at bigint, pack int"


def _first_of_equals(h1: np.ndarray, h2: np.ndarray, doc: np.ndarray, turn: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(places of the first of all equal rows, places of later ones that are other occurrences, for each first whether there are any)."""
    order = np.lexsort((at, turn, doc, at >= 0, h2, h1))
    h1, h2, doc, turn, at = h1[order], h2[order], doc[order], turn[order], at[order]
    same = np.zeros(len(order), dtype=bool)
    same[1:] = (h1[1:] == h1[:-1]) & (h2[1:] == h2[:-1])
    moved = same.copy()
    moved[1:] &= (doc[1:] != doc[:-1]) | (turn[1:] != turn[:-1]) | (at[1:] != at[:-1])
    again = np.append(moved[1:], False)[~same] if len(order) else moved
    return order[~same], order[moved], again


def _batch(route, u1, u2, doc, turn, at, n, kind) -> pa.RecordBatch:
    cols = [x.view(np.int64) if x.dtype == np.uint64 else x.astype(np.int64) for x in (route, u1, u2, doc, turn, at)]
    return pa.RecordBatch.from_arrays([pa.array(x) for x in cols] + [pa.array((kind * 64 + n).astype(np.int32))], ["route", "u1", "u2", "doc", "turn", "at", "pack"])


def _scatter(doc: np.ndarray, turn: np.ndarray, at: np.ndarray) -> np.ndarray:
    return mix(doc.astype(np.int64).view(np.uint64) * np.uint64(5) + mix(turn.astype(np.int64).view(np.uint64) + at.astype(np.int64).view(np.uint64)))


class HotUnits:
    """The least place sent so far of units that repeat, at most ``HOT`` of them."""

    def __init__(self):
        self.sent: dict[tuple[int, int], tuple] = {}

    def split(self, u1: list[int], u2: list[int], places: list[tuple], again: list[bool]) -> np.ndarray:
        """For each distinct unit of a slice: 0 goes on, 1 repeats one that was sent, 2 is the one that was sent."""
        out = np.zeros(len(u1), dtype=np.int8)
        for k, unit in enumerate(zip(u1, u2, strict=True)):
            before = self.sent.get(unit)
            if before is not None and before <= places[k]:
                out[k] = 2 if before == places[k] else 1
            elif before is not None or again[k] and len(self.sent) < HOT:
                self.sent[unit] = places[k]
        return out


def _unit_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc, turn, lost, text) to rows of units."""
    hot, routes = HotUnits(), np.zeros(0, np.uint64)
    for batch in byte_slices(batches, 3, CHUNK_BYTES):
        chunk = Chunk(batch.column(3))
        u = units(chunk)
        text = chunk.text_of(u["first"])
        doc, turn, at = _places(batch, chunk, text, u["first"])
        firsts, repeats, again = _first_of_equals(u["u1"], u["u2"], doc, turn, at)
        known = np.flatnonzero(again | np.isin(u["u1"][firsts], np.fromiter((x[0] for x in hot.sent), np.uint64, len(hot.sent))))
        if len(known):
            of = firsts[known]
            places = list(zip((at[of] >= 0).tolist(), doc[of].tolist(), turn[of].tolist(), at[of].tolist(), strict=True))
            fate = hot.split(u["u1"][of].tolist(), u["u2"][of].tolist(), places, again[known].tolist())
            repeats = np.append(repeats, of[fate == 1])
            firsts = np.delete(firsts, known[fate > 0])
        firsts = firsts[np.argsort(u["key"][firsts], kind="stable")]
        key = u["key"][firsts]
        third = np.zeros(len(key), dtype=bool)
        third[2:] = key[2:] == key[:-2]
        # a representative of which this task has sent two units is known to have several
        third |= np.isin(key, routes)
        if len(routes) < HOT:
            routes = np.union1d(routes, key[third])
        sent, rest = firsts[~third], firsts[third]
        kind = np.concatenate([np.full(len(x), k) for x, k in ((sent, MEETS), (rest, BY_WINDOW), (repeats, REPEAT))])
        of = np.concatenate([sent, rest, repeats])
        meets = kind == MEETS
        zero = np.uint64(0)
        yield _batch(np.where(meets, u["key"][of], _scatter(doc[of], turn[of], at[of])), np.where(meets, u["u1"][of], zero), np.where(meets, u["u2"][of], zero), doc[of], turn[of], at[of], u["n"][of], kind)


def _places(batch: pa.RecordBatch, chunk: Chunk, text: np.ndarray, where: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc, turn, at) of places of a chunk's texts."""
    doc, turn, lost = (batch.column(k).to_numpy(zero_copy_only=False)[text] for k in range(3))
    return doc, turn, where - chunk.first[text] + np.where(lost, LOST, 0)


def _window_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc, turn, lost, text, at array, n array) to rows of the windows named."""
    for batch in byte_slices(batches, 3, CHUNK_BYTES):
        chunk = Chunk(batch.column(3))
        starts, sizes = batch.column(4), batch.column(5)
        of = np.repeat(np.arange(batch.num_rows), starts.value_lengths().to_numpy(zero_copy_only=False))
        at, n = starts.flatten().to_numpy(), sizes.flatten().to_numpy().astype(np.int64)
        step = np.arange(int(n.sum())) - np.repeat(np.append(0, np.cumsum(n)[:-1]), n)
        of, at = np.repeat(of, n), np.repeat(np.where(at < 0, at - LOST, at), n) + step
        h1, h2 = chunk.hashes()
        place = chunk.first[of] + at
        h1, h2 = h1[place], h2[place]
        doc, turn, at = _places(batch, chunk, of, place)
        firsts, repeats, _ = _first_of_equals(h1, h2, doc, turn, at)
        both = np.concatenate([firsts, repeats])
        kind = np.repeat([MEETS, REPEAT], [len(firsts), len(repeats)])
        meets, zero = kind == MEETS, np.uint64(0)
        yield _batch(np.where(meets, h1[both], _scatter(doc[both], turn[both], at[both])), np.where(meets, h1[both], zero), np.where(meets, h2[both], zero), doc[both], turn[both], at[both], np.ones(len(both), dtype=np.int64), kind)


def _met(rows: DataFrame) -> DataFrame:
    """(doc, turn, at, n, repeat, open): after meeting, whether a row repeats an earlier one, and whether its windows are still open."""
    kind = F.shiftright("pack", 6)
    within = Window.partitionBy("route").orderBy("pack_kind", "u1", "u2", F.col("at") >= 0, "doc", "turn", "at")
    whole = within.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = F.lag(F.struct("u1", "u2")).over(within)
    place = F.lag(F.struct("doc", "turn", "at")).over(within)
    meets = F.col("pack_kind") == MEETS
    seen = (
        rows.withColumn("pack_kind", kind)
        .withColumn("same", F.coalesce(before == F.struct("u1", "u2"), F.lit(False)) & meets)
        .withColumn("moved", F.coalesce(place != F.struct("doc", "turn", "at"), F.lit(False)))
        .withColumn("others", F.min("u1").over(whole) != F.max("u1").over(whole))
    )
    return seen.select(
        "doc", "turn", "at", F.col("pack").bitwiseAND(63).alias("n"),
        ((F.col("pack_kind") == REPEAT) | (F.col("same") & F.col("moved"))).alias("repeat"),
        ((F.col("pack_kind") == BY_WINDOW) | (meets & ~F.col("same") & F.col("others"))).alias("open"),
    )


def _with_ranges(rows: DataFrame, marks: DataFrame, how: str) -> DataFrame:
    """Adds (at array, n array), a document's ranges, which its length bounds."""
    ranges = marks.groupBy("doc", "turn", (F.col("at") < 0).alias("lost")).agg(F.collect_list(F.struct("at", "n")).alias("r"))
    return rows.join(ranges, ["doc", "turn", "lost"], how).select("doc", "turn", "lost", "text", F.col("r.at").alias("at"), F.col("r.n").alias("n"))


def _numbered(docs: DataFrame, text: str, key: str) -> DataFrame:
    """(doc, turn, lost, text): what a row is known by, and whether it has no id."""
    rows = docs.select(F.col(key).cast("bigint").alias("id"), F.col(text).alias("text"))
    digest = F.xxhash64(F.coalesce("text", F.lit("")))
    by_id = rows.where("id is not null").groupBy("id").agg((F.min(digest) != F.max(digest)).alias("two"))
    shared = by_id.agg(F.max("two")).first()[0]
    lost = F.col("id").isNull()
    other = F.xxhash64(F.lit("turn"), F.coalesce("text", F.lit("")))
    return rows.select(F.coalesce("id", digest).alias("doc"), F.when(lost, other).otherwise(digest if shared else F.lit(0)).alias("turn"), lost.alias("lost"), "text")


def _remove(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc, turn, lost, text, at, n) to (doc, lost, n_words, n_removed, kept)."""
    for batch in byte_slices(batches, 3, CHUNK_BYTES):
        out = []
        for text, ats, ns in zip(*[batch.column(k).to_pylist() for k in range(3, 6)], strict=True):
            words = (text or "").encode().split()
            gone = np.zeros(len(words) + 1, dtype=np.int64)
            for at, n in zip(ats or [], ns or [], strict=True):
                start = at - LOST if at < 0 else at
                gone[start] += 1
                gone[start + n + WINDOW - 1] -= 1
            keep = np.cumsum(gone[:-1]) == 0
            kept = words if keep.all() else [words[k] for k in np.flatnonzero(keep).tolist()]
            out.append((len(words), len(words) - len(kept), b" ".join(kept)))
        n_words, n_removed, kept = zip(*out, strict=True) if out else ((), (), ())
        columns = [batch.column(0), batch.column(2), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())]
        yield pa.RecordBatch.from_arrays(columns, ["doc", "lost", "n_words", "n_removed", "kept"])


def remove_repeats(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(key, n_words, n_removed, kept): every row's text without words of windows that start earlier elsewhere."""
    rows = _numbered(docs, text, key)
    marks = materialise(_met(rows.mapInArrow(_unit_rows, ROWS)).where("repeat or open"), "unit-marks")
    near = _with_ranges(rows, marks.where("open"), "inner")
    windows = materialise(_met(near.mapInArrow(_window_rows, ROWS)).where("repeat").select("doc", "turn", "at", "n"), "window-marks")
    final = _with_ranges(rows, marks.where("repeat").select("doc", "turn", "at", "n").union(windows), "left")
    done = final.mapInArrow(_remove, "doc bigint, lost boolean, n_words bigint, n_removed bigint, kept string")
    return done.select(F.when(~F.col("lost"), F.col("doc")).alias("key"), "n_words", "n_removed", "kept")


def op7_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document without repeated passages of 20 words and more, as a digest."""
    done = remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return done.select(F.col("key").alias("doc_id"), "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


#: The same rows in DuckDB's dialect.
OP7_SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS words FROM documents),
starts AS (SELECT doc_id, unnest(range(1, greatest(len(words) - 18, 1))) AS i, words FROM w),
wins AS (SELECT doc_id, i, md5(array_to_string(list_slice(words, i, i + 19), ' ')) AS h FROM starts),
later AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY h ORDER BY doc_id, i) AS k FROM wins) WHERE k > 1),
gone AS (SELECT DISTINCT doc_id, i + o AS p FROM later, range(0, 20) r(o)),
each AS (SELECT doc_id, unnest(range(1, len(words) + 1)) AS p, unnest(words) AS word FROM w),
kept AS (SELECT e.doc_id, string_agg(word, ' ' ORDER BY p) AS text, count(*) AS n
         FROM each e LEFT JOIN gone g USING (doc_id, p) WHERE g.doc_id IS NULL GROUP BY e.doc_id)
SELECT w.doc_id, len(words)::BIGINT AS n_words, (len(words) - coalesce(k.n, 0))::BIGINT AS n_removed, sha256(coalesce(k.text, '')) AS kept_sha256
FROM w LEFT JOIN kept k USING (doc_id)
"""
