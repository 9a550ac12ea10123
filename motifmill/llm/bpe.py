"""BPE encoding and decoding with the tokenizers library, exact for texts of any length.

Texts of more than ``PART`` bytes go through tree concatenation: a text is halved down
to parts, wherever the halves fall, the parts of all texts at hand are encoded together,
and neighbours are joined level by level. Around each join a window is encoded again that
begins and ends where no token can cross, at plain white space some way from the join; it
grows until its first token is the left side's and its last one the right side's, and
takes the place of what the sides had there.

A part is encoded by its pieces, between places that no token crosses, with a bounded
memo of the pieces' ids. A text with an unsplit piece of ``LONG`` characters and more
has its own tree over the tokens: the window around a join is a few tokens wide, and grows
until its first token is one that the left side has there and some token near its end is
one that the right side has. Every two neighbouring tokens of the result have then been
neighbours in some encoding, and that makes a sequence of BPE tokens the encoding.

Two ways of cutting are known: ``drop_space`` for tokenizers that lose white space
between words, ``lead_space`` for byte-level ones that attach one space to the word
after it. Special tokens that occur in a text become their ids, as in the library.

Nulls: a null text is the empty text and has no tokens. Repeated rows are encoded
each. A very long text is one row of one task, which holds its ids. An empty table gives
an empty result; columns that are not carried are dropped.
"""

from __future__ import annotations

import os
import re
import struct
from array import array
from codecs import charmap_decode
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from motifmill.llm.words import byte_slices, raw_texts, slices

#: Characters of unsplit text from which the tree is used, and of its leaves.
LONG, LEAF = 8192, 2048
#: Bytes of text from which it is halved, and bytes on each side of a join that its first window has.
PART, NEAR = 1024, 8
#: Bytes of text that are split and looked up at once.
SLICE_BYTES = 2 << 20
#: Pieces in a generation of a worker's memo.
MEMO = 150_000
#: White space of Unicode, fixed values.
WHITE = [*range(0x09, 0x0E), *range(0x1C, 0x21), 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
UNSAFE = [(chr(c) + " ").encode() for c in WHITE if c > 0x7F]
LEADS = sorted({x[:2] for x in UNSAFE})
ASCII_WHITE = bytes(0x0A if c in WHITE and c < 0x20 else c for c in range(256))
STOPS = (b".", b",", b";", b":", b"!", b"?")

#: Where no token crosses in a text and its parts: before a space between letters, digits or stops (byte-level), or any ASCII white space.
BEFORE_SPACE = re.compile(rb"(?<=[0-9A-Za-z.,;:]) (?=[0-9A-Za-z])")
ANY_SPACE = re.compile(rb"[\x20\x09-\x0D]")
UNSPLIT = re.compile(rb"[^\x20\x09-\x0D]{%d}" % LONG)
LATIN_END = "\u0250"
#: Characters that stand for bytes in byte-level vocabularies: printable ones for themselves, the rest from U+0100 on.
_PRINTABLE = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
_REST = iter(range(0x100, 0x200))
#: Little-endian bytes of few ids.
ID_BYTES = [struct.Struct(f"<{n}I").pack for n in range(16)]
BYTE_CHARS = "".join(chr(b) if b in _PRINTABLE else chr(next(_REST)) for b in range(256))


class Span:
    """Tokens of a stretch of unsplit text: ids and the offsets where they end."""

    __slots__ = ("ids", "starts", "ends")

    def __init__(self, ids: list[int], starts: list[int], ends: list[int]):
        self.ids, self.starts, self.ends = ids, starts, ends


def _halves(text: bytes) -> list[bytes]:
    """A text in 2^n parts of about PART bytes at most, cut at characters wherever halving falls."""
    count = 1
    while len(text) > PART * count:
        count *= 2
    bounds = [len(text) * k // count for k in range(count + 1)]
    for k in range(1, count):
        while bounds[k] < len(text) and text[bounds[k]] & 0xC0 == 0x80:
            bounds[k] += 1
    return [text[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]


def _last_cut(cut: re.Pattern, text: bytes, end: int) -> int:
    """Place of the last cut before ``end``, 0 if there is none."""
    step = 64
    while end > 0:
        found = None
        for found in cut.finditer(text, max(0, end - step), end):
            pass
        if found:
            return found.start()
        if step >= end:
            return 0
        step *= 4
    return 0


class Codec:
    """One tokenizer file: encodes and decodes batches of texts."""

    def __init__(self, path: str, memo: int = MEMO):
        self.most = memo
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self.tok = Tokenizer.from_file(path)
        self.tok.no_truncation()
        self.tok.no_padding()
        self.bare = Tokenizer(self.tok.model)  # the model alone: a whole string is one unsplit piece
        self.special = {t.content: i for i, t in self.tok.get_added_tokens_decoder().items()}
        self.split_special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        ids = lambda x: self.tok.encode(x, add_special_tokens=False).ids
        self.lead_space = ids(" b") != ids("b")
        self.memo: dict[bytes | tuple[bytes], bytes] = {}
        self.older: dict[bytes | tuple[bytes], bytes] = {}
        self.joins = self.windows = 0
        self.model = self.tok.model
        self.tokenize = self.model.tokenize
        self.line_end = np.array(ids("\n"), dtype="<u4").tobytes()
        self.lead = charmap_decode(b" ", "strict", BYTE_CHARS)[0] if self.lead_space else ""
        space = " " if self.lead_space else ""
        alone = lambda w: [t for t, _ in self.tok.pre_tokenizer.pre_tokenize_str(self.tok.normalizer.normalize_str(w) if self.tok.normalizer else w)]
        form = lambda w: self.lead + charmap_decode((w if self.lead_space else w.lower()).encode(), "strict", BYTE_CHARS)[0]
        probes = ("a", "Word", "\u00e9t\u00c9", "\u00df\u0131", "\u017f\u00aa", "\u01c5don")
        self.words_alone = self.tok.pre_tokenizer is not None and all(alone(space + w) == [form(w)] for w in probes)
        self.stops = {x: np.array(ids(x.decode()), dtype="<u4").tobytes() for x in STOPS}
        self.tokens = [self.tok.id_to_token(i) or "" for i in range(self.tok.get_vocab_size(with_added_tokens=True))]
        self.plain = self.tok.decoder is None

    # -- encoding -----------------------------------------------------------

    def safe(self, text: bytes) -> bool:
        """Whether every space of a text begins a new piece: none follows other white space."""
        if b"  " in text or b"\n " in text.translate(ASCII_WHITE):
            return False
        return text.isascii() or not any(x in text for x in LEADS) or not any(x in text for x in UNSAFE)

    def encode_column(self, column: pa.Array) -> pa.ListArray:
        """Ids of each text of a string column; null texts have none.

        A column is split and its distinct pieces are numbered by Arrow; the memo is asked once for each distinct piece.
        """
        texts = pc.fill_null(column.cast(pa.string()), "")
        lists = pc.split_pattern(texts, " ") if self.lead_space else pc.ascii_split_whitespace(texts)
        codes = lists.flatten().dictionary_encode()
        ends = np.append(0, np.cumsum(lists.value_lengths().to_numpy(zero_copy_only=False)))
        at, keys = codes.indices.to_numpy(zero_copy_only=False).astype(np.int64), codes.dictionary.cast(pa.binary()).to_pylist()
        odd: dict[int, bytes] = {}
        if self.lead_space:
            # the first piece of a text has no space before it; texts with runs of white space are cut elsewhere
            firsts = [(x,) for x in pc.list_element(lists, 0).cast(pa.binary()).to_pylist()] if len(lists) else []
            at = at.copy()
            at[ends[:-1]] = len(keys) + np.arange(len(firsts))
            keys += firsts
            raw = raw_texts(texts)
            odd = {k: self.encode_unsplit(x.decode()) for k, x in enumerate(raw) if not self.safe(x)}
        ids = self._look_up(keys)
        size = np.array([len(x) >> 2 for x in ids], dtype=np.int64)
        flat, start = np.frombuffer(b"".join(ids), dtype="<i4"), np.append(0, np.cumsum(size))
        count = size[at]
        total = np.append(0, np.cumsum(count))
        place = np.repeat((start[at] - total[:-1]).astype(np.int32), count)
        place += np.arange(total[-1], dtype=np.int32)
        values = flat[place]
        bounds = total[ends]
        if odd:
            parts = [np.frombuffer(odd[k], dtype="<i4") if k in odd else values[bounds[k] : bounds[k + 1]] for k in range(len(bounds) - 1)]
            values, bounds = np.concatenate(parts), np.append(0, np.cumsum([len(x) for x in parts]))
        return pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(values, pa.int32()))

    def encode_texts(self, column: pa.Array) -> pa.ListArray:
        """The same as ``encode_column`` by way of halves, for each text longer than PART; ``joins`` and ``windows`` count what it took."""
        raw = raw_texts(column)
        parts, owners, whole = [], [], {}
        for k, text in enumerate(raw):
            if len(text) > LONG and UNSPLIT.search(text):
                whole[k] = np.frombuffer(self.encode_unsplit(text.decode()), dtype="<i4")
                text = b""
            halves = _halves(text)
            parts += halves
            owners.append(len(halves))
        found = self.encode_column(pa.array(parts, pa.binary()))
        flat, ends = found.values.to_numpy(), found.offsets.to_numpy()
        ids = [flat[a:b] for a, b in zip(ends, ends[1:], strict=False)]
        while len(parts) > len(owners):
            left, at = [], 0
            for n in owners:
                left += range(at, at + n - 1, 2) if n > 1 else []
                at += n
            joined = self._join_parts([(parts[k], ids[k], parts[k + 1], ids[k + 1]) for k in left])
            for k, (text, x) in zip(left, joined, strict=True):
                parts[k], ids[k] = text, x
            gone = {k + 1 for k in left}
            parts, ids = ([x for k, x in enumerate(y) if k not in gone] for y in (parts, ids))
            owners = [n // 2 if n > 1 else 1 for n in owners]
        ids = [whole.get(k, x) for k, x in enumerate(ids)]
        bounds = np.append(0, np.cumsum([len(x) for x in ids])).astype(np.int32)
        return pa.ListArray.from_arrays(pa.array(bounds), pa.array(np.concatenate([*ids, np.zeros(0, np.int32)]), pa.int32()))

    def _join_parts(self, pairs: list[tuple[bytes, np.ndarray, bytes, np.ndarray]]) -> list[tuple[bytes, np.ndarray]]:
        """Text and ids of each two neighbours together, from windows around the joins."""
        cut = BEFORE_SPACE if self.lead_space else ANY_SPACE
        out: list[tuple[bytes, np.ndarray] | None] = [None] * len(pairs)
        near, open_ = NEAR, list(range(len(pairs)))
        while open_:
            tails, heads = [], []
            for k in open_:
                a, _, b, _ = pairs[k]
                tails.append(a[_last_cut(cut, a, len(a) - near) :])
                found = cut.search(b, near) if near < len(b) else None
                heads.append(b[: found.start()] if found else b)
            ids = self.encode_column(pa.array([*tails, *heads, *[t + h for t, h in zip(tails, heads, strict=True)]], pa.binary()))
            flat, ends = ids.values.to_numpy(), ids.offsets.to_numpy()
            n, left = len(open_), []
            self.windows += n
            for j, k in enumerate(open_):
                (tail, head, both), (a, x, b, y) = (flat[ends[i] : ends[i + 1]] for i in (j, n + j, 2 * n + j)), pairs[k]
                agree = (len(tails[j]) == len(a) or both[:1].tolist() == tail[:1].tolist()) and (len(heads[j]) == len(b) or both[-1:].tolist() == head[-1:].tolist())
                if agree:
                    out[k] = a + b, np.concatenate([x[: len(x) - len(tail)], both, y[len(head) :]])
                else:
                    left.append(k)
            open_, near = left, near * 4
        self.joins += len(pairs)
        return out

    def _look_up(self, keys: list) -> list[bytes]:
        """Id bytes of distinct pieces; for byte-level tokenizers a piece comes after a space unless it is in a tuple."""
        if len(self.memo) > self.most:  # two generations: what is asked for again moves to the new one
            self.memo, self.older = {}, self.memo
        memo, older = self.memo, self.older
        found = list(map(memo.get, keys))
        places = [k for k, x in enumerate(found) if x is None]
        if not places:
            return found
        others = []
        lead, tokenize, stops, alone, lower = self.lead, self.tokenize, self.stops, self.words_alone, not self.lead_space
        for k in places:
            x = keys[k]
            ids = older.get(x)
            if ids is None and alone:
                # plain ASCII words, which most pieces are, without a call; the same as ``_word``
                stop = b""
                word = x if type(x) is bytes else b""
                if word and not word.isalpha():
                    stop = stops.get(word[-1:], b"")
                    word = word[:-1] if stop else b""
                if word.isalpha() and len(word) <= LONG:
                    own = [t.id for t in tokenize(lead + (word.lower() if lower else word).decode())]
                    ids = ID_BYTES[len(own)](*own) + stop if len(own) < len(ID_BYTES) else array("I", own).tobytes() + stop
                elif b"\n" in (x if type(x) is bytes else x[0]):
                    ids = self._lines(x)
                    if ids is not None:
                        found[k] = ids  # its words are kept, not the two together
                        continue
                else:
                    ids = self._word(x, lead) if type(x) is bytes else self._word(x[0], "")
            if ids is None:
                others.append(k)
            else:
                memo[x] = found[k] = ids
        if not others:
            return found
        text = lambda x: x[0] if isinstance(x, tuple) else b" " + x if self.lead_space else x
        self._learn([(keys[k], text(keys[k])) for k in others if len(text(keys[k])) <= LONG])
        for k in others:
            ids = memo.get(keys[k])
            found[k] = self.encode_unsplit(text(keys[k]).decode()) if ids is None else ids  # long ones are not kept
        return found

    def encode_batch(self, texts: list[bytes]) -> list[bytes]:
        """Little-endian 32-bit ids of each text."""
        return [np.array(x, dtype="<u4").tobytes() for x in self.encode_column(pa.array(texts, pa.binary())).to_pylist()]

    def _lines(self, piece: bytes | tuple[bytes]) -> bytes | None:
        """Id bytes of a piece of plain words, each with a stop at most, in lines; None for others.

        A letter and the stop after it are never in one token, and a line end between words is a token of its own.
        """
        memo, older, out = self.memo, self.older, []
        inside = isinstance(piece, tuple)
        for line in (piece[0] if inside else piece).split(b"\n"):
            x = (line,) if inside else line
            # only plain ASCII words may come from the memo, which holds other pieces too
            plain = (line[:-1] if line[-1:] in self.stops else line).isalpha()
            ids = memo.get(x) if plain else None
            if ids is None:
                ids = older.get(x) if plain else None
                if ids is None:
                    ids = self._word(line, "" if inside else self.lead)
                if ids is None:
                    return None
                if plain:
                    memo[x] = ids
            out.append(ids)
            inside = True
        return self.line_end.join(out)

    def _word(self, piece: bytes, lead: str) -> bytes | None:
        """Id bytes of letters and a stop, straight from the model: no pattern splits the letters."""
        stop = self.stops.get(piece[-1:], b"")
        if stop:
            piece = piece[:-1]
        word = piece.decode()
        if not word.isalpha() or len(word) > LONG:
            return None
        if not self.lead_space:
            word = word.lower()
            piece = word.encode()
        if not word.isascii():
            if not word.isalpha() or max(word) >= LATIN_END:
                return None
            word = charmap_decode(piece, "strict", BYTE_CHARS)[0]
        return array("I", [t.id for t in self.tokenize(lead + word)]).tobytes() + stop

    def _learn(self, new: list[tuple]) -> None:
        """Encode (key, text) for the memo; a special token between texts keeps them apart and marks their ends."""
        mark, own = next(((t.encode(), i) for t, i in self.special.items()), (None, -1))
        plain = []
        for key, x in new:
            if mark is None or mark in x:
                self.memo[key] = np.array(self.tok.encode(x.decode(), add_special_tokens=False).ids, dtype="<u4").tobytes()
            else:
                plain.append((key, x))
        for at in range(0, len(plain), 32_768):
            groups = [plain[k : k + 256] for k in range(at, min(at + 32_768, len(plain)), 256)]
            for group, e in zip(groups, self.tok.encode_batch_fast([mark.join([x for _, x in g]).decode() for g in groups], add_special_tokens=False), strict=True):
                ids = np.array(e.ids, dtype="<u4")
                data, start = ids.tobytes(), 0
                for (key, _), end in zip(group, [*(np.flatnonzero(ids == own) * 4).tolist(), len(data)], strict=True):
                    self.memo[key] = data[start:end]
                    start = end + 4

    def encode_unsplit(self, text: str) -> bytes:
        """Ids of a long piece: special tokens first, then the library's own splitting, then the tree."""
        ids: list[int] = []
        for part in self.split_special.split(text) if self.split_special else [text]:
            if part in self.special:
                ids.append(self.special[part])
                continue
            part = self.tok.normalizer.normalize_str(part) if self.tok.normalizer else part
            words = [w for w, _ in self.tok.pre_tokenizer.pre_tokenize_str(part)] if self.tok.pre_tokenizer else [part]
            for w in words:
                ids += self.tree(w) if len(w) > LONG else self.bare.encode(w, add_special_tokens=False).ids
        return np.array(ids, dtype="<u4").tobytes()

    def _encode_spans(self, text: str, spans: list[tuple[int, int]]) -> list[Span]:
        before, os.environ["TOKENIZERS_PARALLELISM"] = os.environ.get("TOKENIZERS_PARALLELISM", "false"), "true"
        try:
            found = self.bare.encode_batch([text[a:b] for a, b in spans], add_special_tokens=False)
        finally:
            os.environ["TOKENIZERS_PARALLELISM"] = before
        return [Span(e.ids, [a + x for x, _ in e.offsets], [a + y for _, y in e.offsets]) for (a, _), e in zip(spans, found, strict=True)]

    def tree(self, text: str, leaf: int = LEAF) -> list[int]:
        """Ids of one unsplit string by halves, leaves and joins."""
        count = 1
        while len(text) > leaf * count:
            count *= 2
        bounds = [len(text) * k // count for k in range(count + 1)]
        level = self._encode_spans(text, list(zip(bounds, bounds[1:], strict=False)))
        while len(level) > 1:
            level = self._join_level(text, level)
        return level[0].ids

    def _join_level(self, text: str, level: list[Span]) -> list[Span]:
        out: list[Span | None] = [None] * (len(level) // 2)
        width = 8
        while open_ := [k for k, x in enumerate(out) if x is None]:
            spans = []
            for k in open_:
                left, right = level[2 * k], level[2 * k + 1]
                spans.append((left.starts[max(0, len(left.ids) - width)], right.ends[min(len(right.ids), width) - 1]))
            for k, window in zip(open_, self._encode_spans(text, spans), strict=True):
                out[k] = self._splice(level[2 * k], level[2 * k + 1], window, width)
            width *= 2
        return out

    @staticmethod
    def _splice(left: Span, right: Span, window: Span, width: int) -> Span | None:
        i, j = max(0, len(left.ids) - width), min(len(right.ids), width)
        if i and (window.ids[0], window.ends[0]) != (left.ids[i], left.ends[i]):
            return None
        k, rest = len(window.ids), j
        if j < len(right.ids):
            places = {(right.starts[x], right.ends[x], right.ids[x]): x for x in range(j)}
            for k in range(len(window.ids), 0, -1):
                at = places.get((window.starts[k - 1], window.ends[k - 1], window.ids[k - 1]))
                if at is not None:
                    rest = at + 1
                    break
            else:
                return None
        joined = lambda a, w, b: a[:i] + w[:k] + b[rest:]
        return Span(joined(left.ids, window.ids, right.ids), joined(left.starts, window.starts, right.starts), joined(left.ends, window.ends, right.ends))

    # -- decoding -----------------------------------------------------------

    def decode(self, ids: np.ndarray) -> str:
        """As the library's ``decode`` with special tokens kept."""
        if self.plain:
            return " ".join(map(self.tokens.__getitem__, ids.tolist()))
        return self.tok.decode(ids.tolist(), skip_special_tokens=False)


@lru_cache(maxsize=4)
def codec(path: str, memo: int = MEMO) -> Codec:
    return Codec(path, memo)


def encode_documents(docs: DataFrame, path: str, text: str = "text", key: str = "doc_id", decode: bool = False, carry: tuple[str, ...] = ()) -> DataFrame:
    """(key, ids array<int>) of each row, ``decoded`` from those ids if asked for, and the columns to ``carry`` along."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for batch in byte_slices(batches, 1, SLICE_BYTES):
            ids = own.encode_texts(batch.column(1))
            columns = [batch.column(0), ids]
            if decode:
                flat, ends = ids.values.to_numpy(), ids.offsets.to_pylist()
                columns.append(pa.array([own.decode(flat[a:b]) for a, b in zip(ends, ends[1:], strict=False)], pa.string()))
            yield pa.RecordBatch.from_arrays([*columns, *batch.columns[2:]], [*["key", "ids", "decoded"][: len(columns)], *carry])

    kinds = [("key", docs.schema[key].dataType), *[(c, docs.schema[c].dataType) for c in carry]]
    (_, of), *rest = [(name, kind.simpleString()) for name, kind in kinds]
    schema = f"key {of}, ids array<int>" + ", decoded string" * decode + "".join(f", `{name}` {kind}" for name, kind in rest)
    return docs.select(F.col(key).alias("key"), F.col(text).alias("__text"), *carry).mapInArrow(run, schema)


def decode_documents(encoded: DataFrame, path: str, ids: str = "ids", key: str = "key") -> DataFrame:
    """(key, text) of rows of ids; null ids give null."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path)
        for batch in slices(batches):
            texts = [None if x is None else own.decode(np.array(x, dtype=np.int64)) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["key", "text"])

    kind = encoded.schema[key].dataType.simpleString()
    return encoded.select(F.col(key).alias("key"), F.col(ids).alias("ids")).mapInArrow(run, f"key {kind}, text string")


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Digests of every document's ids and of the text decoded from them."""
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    both = encode_documents(docs, public_tokenizers.path("word_bpe_49k.json"), decode=True)
    return both.select(
        F.col("key").alias("doc_id"),
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2(F.col("decoded"), 256).alias("decoded_sha256"),
    )
