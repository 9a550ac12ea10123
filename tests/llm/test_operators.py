"""Each registered query against a brute-force version over odd documents, and over empty tables."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

import corpus_pipeline
from motifmill.llm import registry

QUERIES = registry.queries()
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def rows(spark, name, folder):
    return [r.asDict() for r in QUERIES[name](spark, folder).collect()]


def by(found, key, value):
    out = Counter()
    for r in found:
        out[(r[key], value(r))] += 1
    return out


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_empty_tables(spark, empty, name):
    assert rows(spark, name, empty) == []


def test_pipeline_on_empty_tables(spark, empty):
    assert corpus_pipeline.run(spark, empty).collect() == []


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_same_as_sql(spark, odd, name):
    folder, _ = odd
    if name == "op7_substrings":
        pytest.skip("rows without id and repeated rows are compared by brute force")
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{folder}/documents.parquet/*.parquet'")
    mine = QUERIES[name](spark, folder)
    columns = sorted(mine.columns)
    theirs = con.execute(f"select {', '.join(columns)} from ({registry.oracle_sql()[name]})").fetchall()
    if name == "op3_quality_rules":
        keep = [k for k, c in enumerate(columns) if c not in ("n_repeat_words", "base_failed", "kept")]  # SQL cannot tell rows with one id apart
        cut = lambda r: repr(tuple(r[k] for k in keep))
        assert sorted(map(cut, mine.select(columns).collect())) == sorted(map(cut, theirs))
    else:
        assert sorted(map(repr, map(tuple, mine.select(columns).collect()))) == sorted(map(repr, theirs))


def test_quality_base(spark, odd):
    folder, documents = odd

    def base(text):
        text = text or ""
        words, lines = WORD.findall(text), [x for x in text.split("\n") if WORD.search(x)]
        windows = defaultdict(list)
        for k in range(len(words) - 4):
            windows[tuple(words[k : k + 5])].append(k)
        again = {k + j for at in windows.values() if len(at) > 1 for k in at for j in range(5)}
        failed = len(words) < 10 or 100 * len(again) > 20 * len(words)
        return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(again), failed

    found = rows(spark, "op3_quality_rules", folder)
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    assert by(found, "doc_id", lambda r: tuple(r[n] for n in names)) == Counter((d[0], base(d[1])) for d in documents)
    assert not any(r["kept"] and r["base_failed"] for r in found)
    assert any(r["kept"] for r in found)


def test_bad_host_is_rejected(spark, tmp_path):
    from motifmill.llm.quality import quality_verdicts

    good = "plain words stand here in a row and none of them comes twice at all"
    docs = [(k, good if k % 10 == 0 else "x", "bad") for k in range(400)] + [(1000 + k, good, "fine") for k in range(400)]
    out = quality_verdicts(spark.createDataFrame(docs, "doc_id long, text string, source string")).collect()
    assert not any(r.kept for r in out if r.source == "bad") and all(r.kept for r in out if r.source == "fine")
    assert all(0 < r.host_rate < 1 for r in out)


def planted_hosts():
    """Twenty hosts whose documents fail once in ten, and one where almost half fail."""
    good = lambda k: " ".join(f"word{k}and{j}" for j in range(12))
    docs = [(h * 1000 + k, "x" if k % 10 == 0 else good(h * 1000 + k), f"host{h}") for h in range(20) for k in range(200)]
    return docs + [(90_000 + k, "x" if k % 20 < 9 else good(90_000 + k), "bad") for k in range(200)]


def test_host_verdict_decides_in_query_and_pipeline(spark, tmp_path):
    spark.createDataFrame(planted_hosts(), "doc_id long, text string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    found = rows(spark, "op3_quality_rules", str(tmp_path))
    assert {r["doc_id"] for r in found if r["host_failed"]} == set(range(90_000, 90_200))
    kept = {r["doc_id"] for r in found if r["kept"]}
    assert kept == {i for i, t, h in planted_hosts() if t != "x" and h != "bad"}
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    left = corpus_pipeline.quality_stage(spark, docs, "")
    assert left.columns == docs.columns and {r.doc_id for r in left.collect()} == kept
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{tmp_path}/documents.parquet/*.parquet'")
    assert {r[0] for r in con.execute(f"select doc_id from ({registry.oracle_sql()['op3_quality_rules']}) where kept").fetchall()} == kept


def test_bpe(spark, odd):
    folder, documents = odd
    tok = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = Counter()
    for d in documents:
        ids = tok.encode(d[1] or "", add_special_tokens=False).ids
        want[(d[0], (len(ids), sha(" ".join(map(str, ids))), sha(tok.decode(ids, skip_special_tokens=False))))] += 1
    assert by(rows(spark, "op4_bpe", folder), "doc_id", lambda r: (r["n_tokens"], r["ids_sha256"], r["decoded_sha256"])) == want


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_codec_and_tree(name):
    import random

    from motifmill.llm.bpe import Codec

    own, tok, rng = Codec(public_tokenizers.path(name)), Tokenizer.from_file(public_tokenizers.path(name)), random.Random(3)
    for _ in range(800):
        text = "".join(rng.choice("ab cé\n 'st  <|endoftext|>́Σß漢 1.\t \x1c\x85İ") for _ in range(rng.randint(0, 50)))
        ids = np.frombuffer(own.encode_batch([text.encode()])[0], "<u4")
        assert ids.tolist() == tok.encode(text, add_special_tokens=False).ids
        assert own.decode(ids) == tok.decode(ids.tolist(), skip_special_tokens=False)
    for _ in range(150):
        piece = "".join(rng.choice(rng.choice(["ab", "abcdefgh", "thequickbrown", "aaab"])) for _ in range(rng.randint(20, 400)))
        assert own.tree(piece, leaf=rng.choice([3, 8, 17])) == own.bare.encode(piece, add_special_tokens=False).ids
    long = "the" * 6000 + "a" * 9000 + "x<|endoftext|>" + "".join(rng.choice("abcdefghij") for _ in range(20000))
    assert np.frombuffer(own.encode_batch([long.encode()])[0], "<u4").tolist() == tok.encode(long, add_special_tokens=False).ids


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "byte_bpe_50k.json"])
def test_halves_of_texts(name, monkeypatch):
    """Texts halved wherever halves fall, special tokens and white space included, against the library."""
    import random

    import pyarrow as pa

    from motifmill.llm import bpe

    monkeypatch.setattr(bpe, "PART", 8)
    own, tok, rng = bpe.Codec(public_tokenizers.path(name)), Tokenizer.from_file(public_tokenizers.path(name)), random.Random(6)
    bits = ["the", "quick ", "  ", "a", " ", "c", "é", "\n", " 'st", " don't", "<|endoftext|>", "\u0301", "Σ", "ß", "漢", "1", ".", "\t", "\x1c", "\x85", " word", " go,"]
    texts = ["".join(rng.choices(bits, k=rng.randint(0, 70))) for _ in range(600)]
    found = own.encode_texts(pa.array([None, *texts])).to_pylist()
    assert found[0] == [] and own.joins > 3000
    for text, ids in zip(texts, found[1:], strict=True):
        assert ids == tok.encode(text, add_special_tokens=False).ids


def test_bpe_round_trip(spark):
    from motifmill.llm.bpe import decode_documents, encode_documents

    path = public_tokenizers.path("byte_bpe_50k.json")
    docs = spark.createDataFrame([(1, "Two  spaces,\nlines é 漢."), (2, ""), (3, None)], "doc_id long, text string")
    back = {r.key: r.text for r in decode_documents(encode_documents(docs, path), path).collect()}
    assert back == {1: "Two  spaces,\nlines é 漢.", 2: "", 3: ""}


def luhn(digits):
    odd = [int(x) for x in digits[::-1]]
    return sum(x if k % 2 == 0 else (2 * x - 9 if x > 4 else 2 * x) for k, x in enumerate(odd)) % 10 == 0


def base_spans(text):
    out = [("email", m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    out += [("ip", m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(x) <= 255 for x in m[0].split("."))]
    only = lambda s: re.sub("[^0-9]", "", s)
    out += [("card", m.start(), m.end()) for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text) if 13 <= len(only(m[0])) <= 19 and luhn(only(m[0]))]
    return out + [("phone", m.start(), m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 9 <= len(only(m[0])) <= 15]


def test_pii(spark, odd):
    import random

    from motifmill.llm.pii import BASE, redact, text_spans

    rng = random.Random(1)
    for k in range(8000):
        text = "".join(rng.choice("0123456789012345678 -" if k % 3 == 0 else "0123456789..@@a-+ ()%é٣") for _ in range(rng.randint(0, 60)))
        assert [s for s in text_spans(text) if s[0] in BASE] == base_spans(text)
    folder, documents = odd
    want = Counter()
    for d in documents:
        spans = base_spans(d[1] or "")
        kinds = Counter(s[0] for s in spans)
        want[(d[0], (*[kinds[k] for k in BASE], hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()))] += 1
    found = rows(spark, "op5_pii", folder)
    assert by(found, "doc_id", lambda r: (*[r[f"n_{k}"] for k in BASE], r["base_sha256"])) == want
    text = 'see https://a.org/x?y=1, token = "abcdef0123456789" IBAN: GB82 WEST 1234 5698 7654 32 and account 12345678.'
    assert [s[0] for s in text_spans(text)] == ["url", "iban", "account", "secret"]
    assert "WEST" not in redact(text, text_spans(text)) and "abcdef" not in redact(text, text_spans(text))


def leaked(text, item, stride):
    """Whether a passage of two strides has 80 % of the shingles of an item, or of its question and its answer; written apart from the operator."""

    def bare(word):
        return re.sub(r"^[\W_]+|[\W_]+$", "", word.lower())

    def grams(words):
        words = [w for w in map(bare, words) if w]
        return [" ".join(words[k : k + 5]) for k in range(max(1, len(words) - 4))] if words else []

    words, doc = item.split(), (text or "").split()
    ends = [k + 1 for k, w in enumerate(words[:-1]) if re.search(r"[.?!][\"')]*$", w)]
    cut = ends[-1] if ends else 0
    question, answer = grams(words[:cut]), grams(words[cut:])
    question, answer = question or answer, answer or question
    if not grams(words):
        return False
    for at in range(0, max(1, len(doc) - stride), stride):
        own = [w for w in map(bare, doc[at : at + 2 * stride]) if w]
        has = lambda g: any(own[j : j + len(g.split(" "))] == g.split(" ") for j in range(len(own)))
        share = lambda gs: sum(map(has, gs)) / len(gs)
        if share(grams(words)) >= 0.8 or min(share(question), share(answer)) >= 0.8:
            return True
    return False


def test_decontamination(spark, odd, monkeypatch):
    from motifmill.llm import decontaminate as D

    folder, documents = odd
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{folder}/benchmark.parquet").collect() if r.text]
    stride = max(64, max(len(t.split()) for _, t in items))
    want = {(d[0], i) for d in documents for i, t in items if leaked(d[1], t, stride)}
    assert want and {(r["doc_id"], r["item_id"]) for r in rows(spark, "op6_decontaminate", folder)} == want
    monkeypatch.setattr(D, "PART_BYTES", 150)  # several indexes give the same
    monkeypatch.setattr(D, "CELLS", 4)
    assert {(r["doc_id"], r["item_id"]) for r in rows(spark, "op6_decontaminate", folder)} == want


def test_pivots_find_what_scoring_all_items_finds():
    import random

    from motifmill.llm.decontaminate import BlockMaxIndex

    rng = random.Random(5)
    words = [f"w{k}" for k in range(80)]
    index = BlockMaxIndex([(k, " ".join(rng.choices(words, weights=range(1, 81), k=rng.randint(3, 25)))) for k in range(150)])
    full = 0
    for _ in range(200):
        terms = sorted({index.terms[w] for w in rng.choices(words, k=rng.randint(1, 60)) if w in index.terms})
        score = np.zeros(len(index.items))
        for t in terms:
            score[index.item[index.first[t] : index.first[t + 1]]] += index.weight[index.first[t] : index.first[t + 1]]
        want = {k for k in range(len(score)) if score[k] >= 1 + 1e-9}
        found = index.search(np.zeros(len(terms), np.int64), np.array(terms), 1)
        assert want <= {i for _, i, _ in found} and all(abs(score[i] - x) < 1e-9 for _, i, x in found)
        full += len(want)
    assert full > 100


def test_items_with_unicode_white_space(spark):
    from motifmill.llm.decontaminate import drop_leaking, find_leaks

    for space in (" ", "\u3000", "\u00a0"):
        item = space.join(f"w{k}" for k in range(200))
        docs = spark.createDataFrame([(1, item, "x"), (2, "clean text", "y"), (3, None, "z")], "doc_id long, text string, key string")
        items = spark.createDataFrame([(7, item), (None, item), (None, None)], "item_id long, text string")
        assert {(r.key, r.item_id) for r in find_leaks(docs, items).collect()} == {(1, 7), (1, None)}
        assert {r.doc_id for r in drop_leaking(docs, items).collect()} == {2, 3}


def test_substrings(spark, odd):
    from motifmill.llm.substrings import remove_repeats

    folder, documents = odd
    first = sorted({(-1 if d[0] is None else d[0], xxhash.xxh64_intdigest((d[1] or "").encode(), 42) - (1 << 64) * (xxhash.xxh64_intdigest((d[1] or "").encode(), 42) >> 63), d[1] or "") for d in documents})
    seen, want = set(), {}
    for i, _, text in first:
        words, gone = WORD.findall(text), set()
        for k in range(len(words) - 19):
            window = tuple(words[k : k + 20])
            gone |= set(range(k, k + 20)) if window in seen else set()
            seen.add(window)
        want[i, text] = (len(words), len(gone), " ".join(w for k, w in enumerate(words) if k not in gone))
    source = spark.read.parquet(f"{folder}/documents.parquet")
    found = Counter((r.key, r.n_words, r.n_removed, r.kept) for r in remove_repeats(source).collect())
    assert found == Counter((d[0], *want[-1 if d[0] is None else d[0], d[1] or ""]) for d in documents)


def test_substrings_of_short_tables(spark):
    from motifmill.llm.substrings import remove_repeats

    long = lambda a, n=30: " ".join(f"{a}{k}" for k in range(n))
    for docs, parts in [([(1, "x y")], 1), ([(1, None)], 1), ([(1, "a b c"), (2, "d e")], 1), ([(1, "a b c"), (2, "d e")], 2), ([(None, None)], 1)]:
        out = remove_repeats(spark.createDataFrame(docs, "doc_id long, text string").repartition(parts)).collect()
        assert sorted((r.key or 0, r.n_removed, r.kept) for r in out) == sorted((i or 0, 0, t or "") for i, t in docs)
    docs = [(-(2**63), long("a")), (None, long("a")), (None, long("a")), (None, long("c")), (5, long("a")), (5, long("b")), (7, long("b")), (7, long("b"))]
    for parts in (1, 8):
        out = remove_repeats(spark.createDataFrame(docs, "doc_id long, text string").repartition(parts)).collect()
        assert Counter((r.key, r.n_removed) for r in out) == Counter([(-(2**63), 30), (None, 0), (None, 0), (None, 0), (5, 30), (5, 0), (7, 30), (7, 30)])


def test_hot_units_of_a_task(monkeypatch):
    """A passage in every text, cut into many slices: a task sends its units once."""
    import pyarrow as pa

    from motifmill.llm import substrings as S

    monkeypatch.setattr(S, "CHUNK_BYTES", 20_000)
    passage = " ".join(f"p{k}" for k in range(60))
    texts = [f"{' '.join(f't{i}x{k}' for k in range(20))} {passage} {' '.join(f's{i}x{k}' for k in range(20))} {passage}" for i in range(300)]
    batch = pa.RecordBatch.from_arrays([pa.array(range(300), pa.int64()), pa.array([0] * 300, pa.int64()), pa.array([False] * 300), pa.array(texts)], ["doc", "turn", "lost", "text"])
    sent = Counter()
    for out in S._unit_rows(iter([batch])):
        for route, pack in zip(out.column(0).to_pylist(), out.column(6).to_pylist(), strict=True):
            sent[route] += pack >> 6 == S.MEETS
    assert max(sent.values()) <= 4


def test_simhash(spark, odd):
    from motifmill.llm.simhash import GrayIndex, fingerprints, gray_rank, similar_links
    from motifmill.llm.components import star_components
    from pyspark.sql import functions as F

    folder, documents = odd

    def code(text):
        words = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
        if not words:
            return 0
        h = [xxhash.xxh64_intdigest(" ".join(words[k : k + 3]).encode(), 42) for k in range(max(1, len(words) - 2))]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    codes = [(d[0], code(d[1])) for d in documents]
    label = {c: min((i for i, x in codes if x == c and i is not None), default=None) for _, c in codes}
    changed = True
    while changed:
        changed = False
        for a in label:
            for b in label:
                if (a ^ b).bit_count() <= 3 and None not in (label[a], label[b]) and label[b] < label[a]:
                    label[a], changed = label[b], True
    assert by(rows(spark, "op8_simhash", folder), "doc_id", lambda r: (r["fingerprint"], r["component_id"])) == Counter((i, (f"{c:016x}", label[c])) for i, c in codes)
    rng = np.random.default_rng(0)
    seeds = rng.integers(0, 1 << 63, 30, dtype=np.uint64)
    near = np.unique(np.concatenate([seeds ^ np.uint64(1 << int(rng.integers(64))) ^ np.uint64(1 << int(rng.integers(64))) for _ in range(40)]))
    near = near[np.argsort(gray_rank(near))]
    who, met = GrayIndex.of(near).near(near)
    assert {(int(near[a]), int(near[b])) for a, b in zip(who, met, strict=True)} == {(int(x), int(y)) for x in near for y in near if (int(x) ^ int(y)).bit_count() <= 3}
    frame = spark.createDataFrame([(int(c.view(np.int64)), k) for k, c in enumerate(near)], "fp long, root long")
    whole = sorted(map(tuple, star_components(similar_links(frame)).collect()))
    assert whole and sorted(map(tuple, star_components(similar_links(frame, 60)).collect())) == whole
    assert fingerprints(frame.select(F.col("fp").alias("doc_id"), F.lit(None).cast("string").alias("text"))).where("fp <> 0").isEmpty()


def test_gray_index_rules_out_groups_of_the_given_table(spark):
    """All fingerprints of a given table: nearly all comparisons end at an upper node, and no link is lost."""
    from motifmill.llm.components import star_components
    from motifmill.llm.simhash import GrayIndex, fingerprints, gray_rank, similar_links
    from pyspark.sql import functions as F

    codes = fingerprints(spark.read.parquet("/root/testdata/sf0.1/documents.parquet")).groupBy("fp").agg(F.min("key").alias("root")).cache()
    rows = codes.collect()
    near, root = np.array([r.fp for r in rows]).view(np.uint64), [r.root for r in rows]
    pairs = [(root[a], root[b]) for a in range(len(near)) for b in np.flatnonzero(np.bitwise_count(near[a] ^ near[a + 1 :]) <= 3) + a + 1]
    label = {r: r for r in root}
    for _ in pairs:  # a round for each pair is more than enough
        for a, b in pairs:
            label[a] = label[b] = min(label[a], label[b])
    found = {r.node: r.component for r in star_components(similar_links(codes)).collect()}
    assert pairs and all(found.get(r, r) == label[r] for r in root)
    near = near[np.argsort(gray_rank(near))]
    index = GrayIndex.of(near)
    index.near(near)
    assert index.pruned > 0.9 * len(near) ** 2 and index.compared < 0.1 * len(near) ** 2


def test_sharding(spark, odd):
    from motifmill.llm.sharding import ring_shards
    from pyspark.sql import functions as F

    folder, documents = odd
    found = rows(spark, "op9_ring_sharding", folder)
    raw = lambda t: (t or "").encode()
    assert by(found, "doc_id", lambda r: (r["size"], r["text_crc32"])) == Counter((d[0], (len(raw(d[1])) + 16, zlib.crc32(raw(d[1])))) for d in documents)
    slots = defaultdict(list)
    for r in found:
        slots[r["shard"]].append(r["slot"])
    sizes = [len(slots[k]) for k in range(40)]
    assert max(sizes) - min(sizes) <= 1 and all(sorted(x) == list(range(len(x))) for x in slots.values())
    many = spark.range(6000).withColumnRenamed("id", "doc_id")
    place = lambda n, slack: {r.doc_id: r.shard for r in ring_shards(many, n, F.col("doc_id"), ["doc_id"], slack=slack).collect()}
    a, b = place(10, 0.1), place(11, 0.1)
    assert max(Counter(a.values()).values()) <= 660
    assert sum(a[k] != b[k] for k in a) < 0.3 * len(a)  # a plain modulo would move nine of ten


def test_placement_against_a_walk_of_single_documents(spark):
    """Every document of a ring placed one by one, as the operator states it: own shards first, then clockwise, nearest arcs first."""
    from motifmill.llm.sharding import capacities, ring_points, ring_shards
    from pyspark.sql import functions as F

    docs = spark.range(3000).withColumn("doc_id", F.col("id") * 7).drop("id")
    spots = {r.doc_id: r.at for r in docs.select("doc_id", F.xxhash64(F.lit("key"), "doc_id").alias("at")).collect()}
    for slack in (0.0, 0.2):
        ring = [(r.point, r.shard) for r in ring_points(spark, 10, 16).orderBy("arc").collect()]
        room, place, waiting = capacities(3000, 10, slack), {}, [[] for _ in ring]
        for i in sorted(spots, key=lambda i: (spots[i], i)):
            waiting[next((k for k, (p, _) in enumerate(ring) if p >= spots[i]), 0)].append(i)
        wrapped = [i for i in waiting[0] if spots[i] > ring[-1][0]]
        waiting[0] = sorted([i for i in waiting[0] if i not in set(wrapped)] + wrapped, key=lambda i: (spots[i], i))
        for step in range(len(ring)):
            for arc, docs_left in enumerate(waiting):
                shard = ring[(arc + step) % len(ring)][1]
                while docs_left and room[shard]:
                    place[docs_left.pop(0)] = shard
                    room[shard] -= 1
        found = {r.doc_id: r.shard for r in ring_shards(docs, 10, F.col("doc_id"), ["doc_id"], vnodes=16, slack=slack).collect()}
        assert found == place


def test_hot_arc_and_movement(spark, monkeypatch):
    """Half of all rows share a key, in parts of a few rows; and what a forty-first shard moves at the registered slack."""
    from motifmill.llm import sharding as R
    from pyspark.sql import functions as F

    docs = spark.range(4000).select(F.when(F.col("id") < 2000, 5).otherwise(F.col("id")).alias("doc_id"), F.col("id").alias("n"))
    monkeypatch.setattr(R, "HOT_ARC", 300)
    found = R.ring_shards(docs, 8, F.col("doc_id"), ["doc_id"]).collect()
    slots = defaultdict(list)
    for r in found:
        slots[r.shard].append(r.slot)
    assert {r.n for r in found} == set(range(4000)) and all(sorted(x) == list(range(500)) for x in slots.values())
    ids = spark.range(20000).withColumnRenamed("id", "doc_id")
    a, b = ({r.doc_id: r.shard for r in R.ring_shards(ids, n, F.col("doc_id"), ["doc_id"]).collect()} for n in (40, 41))
    assert sum(a[i] != b[i] for i in a) < 0.25 * len(a)  # even loads move more than the fortieth that a bare ring moves


def test_token_shards(spark, odd, tmp_path):
    from motifmill.llm.sstable import ShardReader, TokenTable, read_shards, write_shards

    folder, documents = odd
    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    encode = lambda t: tok.encode(t or "", add_special_tokens=False).ids + [0]
    found = sorted(rows(spark, "op10_token_shards", folder), key=lambda r: r["start"])
    assert [r["doc_id"] for r in found] == sorted((d[0] for d in documents), key=lambda i: (i is not None, i or 0))
    assert by(found, "doc_id", lambda r: (r["n_tokens"], r["ids_crc32"])) == Counter((d[0], (len(encode(d[1])), zlib.crc32(np.array(encode(d[1]), "<u4").tobytes()))) for d in documents)
    start = 0
    for r in found:
        assert r["start"] == start
        start += r["n_tokens"]
    where = f"file://{tmp_path}/shards"
    manifest = write_shards(spark.read.parquet(f"{folder}/documents.parquet"), where, public_tokenizers.path("byte_bpe_50k.json")).orderBy("shard").collect()
    back = read_shards(spark.createDataFrame(manifest), where).collect()
    assert Counter((r.key, tuple(r.ids)) for r in back) == Counter((d[0], tuple(encode(d[1]))) for d in documents)
    table = TokenTable([(m.name, m.first_id, m.last_id) for m in manifest], where)
    assert [x.tolist() for x in table.get(6)] == [encode(documents[6][1])] and table.get(10**9) == [] and len(table.get(None)) == 2
    with pytest.raises(ValueError):
        ShardReader.of_bytes(b"x" * 100)


def test_licenses(spark):
    from motifmill.llm.licenses import CUE, KNOWN, canonical, digests, scan_licenses

    assert all(re.search(CUE, t) for _, t in KNOWN)
    of = dict(reversed(KNOWN))
    first = {n: t for n, t in reversed(KNOWN) if "\n" in t}
    mit = first["MIT"]
    other = "Copyright (c) 2020 Someone\nAll rights reserved.\n" + mit.upper().replace("SUBLICENSE", "sub-licence").replace(",", " ,")
    wrap = lambda t, n, mark="": "\n".join(mark + " ".join(t.split()[k : k + n]) for k in range(0, len(t.split()), n))
    docs = [(1, mit), (2, other), (3, "text\nReleased under the MIT licence!\nmore"), (4, None), (5, ""), (6, mit + " and more"), (7, "plain")]
    docs += [(8, "The MIT License (MIT)\n\nCopyright © 2021 J. Smith Inc.\n\n" + wrap(mit, 9, " * ")), (9, "(c) 2020 X. Licensed under the MIT License.")]
    wrapped = {10 + k: n for k, n in enumerate(sorted(first))}
    docs += [(i, "Copyright (c) <year> <owner>.\n" + wrap(first[n], 7)) for i, n in wrapped.items()]
    docs.append((30, "purpose with or without fee is hereby granted, provided that the above\ncopyright notice and this permission notice appear in all copies."))
    out = {r.key: (r.license, r.line_licenses) for r in scan_licenses(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert out[1][0] == out[2][0] == out[8][0] == "MIT" and out[3] == (None, "MIT") and out[6][0] is None and out[4] == out[5] == out[7] == (None, "")
    assert out[9] == ("MIT", "MIT") and all(out[i][0] == n for i, n in wrapped.items()) and out[30] == (None, "")
    assert canonical("The  Organisation's LICENCE") == "the organization s license"
    own = digests([("house rules", "Take off your shoes.\nBe kind."), ("none", "...")])
    rows_ = spark.createDataFrame([(1, "take OFF your shoes, be kind"), (2, "Take off your shoes")], "doc_id long, text string")
    assert {r.key: r.license for r in scan_licenses(rows_, known=own).collect()} == {1: "house rules", 2: None}
    assert {r.license for r in scan_licenses(rows_, known={}).collect()} == {None} and len(of) > 5


def test_long_license_texts(spark):
    import os

    from motifmill.llm.licenses import scan_licenses

    folder = "/usr/share/common-licenses"
    names = {"Apache-2.0": "Apache-2.0", "GPL-2": "GPL-2.0", "GPL-3": "GPL-3.0", "LGPL-2.1": "LGPL-2.1", "MPL-2.0": "MPL-2.0", "CC0-1.0": "CC0-1.0"}
    texts = [(n, open(f"{folder}/{f}", encoding="utf-8", errors="replace").read()) for f, n in names.items() if os.path.exists(f"{folder}/{f}")]
    docs = [(n, " ".join(t.split())) if n == "MPL-2.0" else (n, t.upper()) for n, t in texts]
    if not docs:
        pytest.skip("this system has no folder of license texts")
    out = {r.key: r.license for r in scan_licenses(spark.createDataFrame(docs, "doc_id string, text string")).collect()}
    assert out == {n: n for n, _ in docs}


def test_chat(spark, odd):
    from motifmill.llm.chat import BEGIN, as_transcript, decode_rows, fit, observed
    from pyspark.sql import functions as F

    folder, _ = odd
    found = rows(spark, "op2_chat_format", folder)
    assert len(found) == spark.read.parquet(f"{folder}/conversations.parquet").count() and all(r["rendered"] is not None for r in found)
    turns = spark.read.parquet("/root/testdata/sf0.01/conversations.parquet")
    train, held = turns.where("conv_id % 2 = 0"), turns.where("conv_id % 2 = 1")
    model = fit(as_transcript(train))
    test = as_transcript(held)
    truth = {(r.id, r.pos): r.role for r in test.collect()}
    roles = ["system", "user", "assistant"]
    states = {(r.id, r.pos): r.states for r in decode_rows(test, model).collect()}
    assert sum(roles[s[0] % 3] == truth[k] for k, s in states.items()) > 0.85 * len(truth)
    one = test.select(F.lit(1).alias("id"), (F.col("id") * 20 + F.col("pos")).alias("pos"), "text")  # one long transcript, in many levels of blocks
    obs = {r.pos: r.obs for r in observed(one).collect()}

    def score(fan):
        got, before, total = {r.pos: r.states for r in decode_rows(one, model, fan).collect()}, BEGIN, 0
        for pos in sorted(obs):
            for o, s in zip(obs[pos], got[pos], strict=True):
                total, before = total + model.line(o)[before, s], s
        return total

    assert score(3) == score(10**6)


def test_chat_against_a_plain_viterbi(spark):
    """Whole transcripts by the textbook recurrence, in plain Python; and the rendering written again."""
    from motifmill.llm.chat import BEGIN, MARKERS, ROLES, STATES, as_transcript, fit, format_transcripts, observed
    from motifmill.llm.chat import decode_rows

    turns = spark.read.parquet("/root/testdata/sf0.001/conversations.parquet")
    rows_ = as_transcript(turns.where("conv_id < 60"))
    model = fit(as_transcript(turns.where("conv_id >= 60")))
    talks = defaultdict(list)
    for r in sorted(observed(rows_).collect(), key=lambda r: (r.id, r.pos)):
        talks[r.id].append((r.pos, r.text, r.obs))
    states = {(r.id, r.pos): r.states for r in decode_rows(rows_, model, 4).collect()}
    formatted = {(r.id, r.pos): r for r in format_transcripts(rows_, model, 4).collect()}
    marker = re.compile(rf"^\s*({'|'.join(m for ms in MARKERS.values() for m in ms)})\s*:\s?")
    assert len(formatted) == sum(map(len, talks.values()))
    for i, talk in talks.items():
        best = {BEGIN: 0}
        for o in (o for _, _, obs in talk for o in obs):
            best = {s: max(score + int(model.step[b, s]) for b, score in best.items()) + int(model.emit[s, o]) for s in range(STATES) if s != BEGIN}
        score, before = 0, BEGIN
        for pos, text, obs in talk:
            for o, s in zip(obs, states[i, pos], strict=True):
                score, before = score + int(model.step[before, s] + model.emit[s, o]), s
            parts = [f"<|{ROLES[s]}|>\n{marker.sub('', x, count=1)}" if s < 3 else x for x, s in zip((text or "").split("\n"), states[i, pos], strict=True)]
            r = formatted[i, pos]
            assert (r.rendered, r.n_turns, r.role) == ("\n".join(parts), sum(s < 3 for s in states[i, pos]), ROLES[states[i, pos][0] % 3])
        assert score == max(best.values())


def test_chat_rows_without_id_or_position(spark):
    from motifmill.llm.chat import as_transcript, decode_rows, fit

    turns = spark.read.parquet("/root/testdata/sf0.001/conversations.parquet")
    model = fit(as_transcript(turns))
    docs = [(None, None, f"User: lost {k}") for k in range(300)] + [(1, None, f"User: where {k}") for k in range(300)] + [(2, 5, "Assistant: same")] * 50 + [(2, -3, None), (2, 2**40, "x\ny")]
    out = decode_rows(spark.createDataFrame(docs, "id long, pos long, text string"), model, 8).collect()
    assert Counter((r.id, r.pos, r.text) for r in out) == Counter(docs)
    assert all(len(r.states) == len((r.text or "").split("\n")) for r in out)


def test_pipeline(spark, odd):
    folder, _ = odd
    names = spark.read.parquet(f"{folder}/documents.parquet").columns
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, docs, folder)
        assert out.columns == names or k == len(corpus_pipeline.STAGES) - 1
        docs = spark.createDataFrame(out.collect(), out.schema)
    kept = docs.collect()
    assert 0 < len(kept) < 40 and all(r.n_tokens == len(r.ids) for r in kept)
    texts = [r.text for r in kept]
    assert len(set(texts)) == len([t for r, t in zip(kept, texts, strict=True) if r.doc_id is not None]) or None in [r.doc_id for r in kept]
