"""Small corpora with every odd case, written as the tables that the queries read."""

import random

import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, key string, fp int, shard string, slot int, kept string, u int, route string, spans string, n_words string"


def odd_documents() -> list[tuple]:
    rng = random.Random(4)
    words = [f"w{i}" for i in range(60)] + ["Été", "naïve,", "x.", "漢字", "a|b", "###"]
    line = lambda n: " ".join(rng.choice(words) for _ in range(n))
    base = [line(120) for _ in range(6)]
    texts = [None, "", " \n\t ", "one", "a b", *base, base[0], base[0], base[1] + " tail", line(40) + " " + base[2][:200], "z" * 30_000, line(4000)]
    texts += ["the same line again here\n" * 9, "mail a.b@c-d.org and +1 (555) 010-9999, 10.0.0.1 4111 1111 1111 1111", "spam " * 50, "<|endoftext|> x<|startoftext|>  y\n\n z", " lead", "trail "]
    texts += [line(rng.randint(0, 60)) for _ in range(30)]
    rows = [(k, t, rng.choice(["en", None]), rng.choice(["s0", "s0", "s1", None])) for k, t in enumerate(texts)]
    rows += [rows[5], (None, base[3], None, None), (None, None, None, None)]  # a repeated row, rows without an id
    return [(i, t, g, s, len(t) if t else None, "x", 1, None, 2, "y", 3, "r", "q", "n") for i, t, g, s in rows]


def write(spark, folder, documents, benchmark=(), conversations=()):
    spark.createDataFrame(documents, SCHEMA).repartition(3).write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(list(benchmark), "item_id bigint, text string, key string").write.parquet(f"{folder}/benchmark.parquet")
    spark.createDataFrame(list(conversations), "conv_id bigint, turn int, role string, text string, id string, pos string").write.parquet(f"{folder}/conversations.parquet")
    return str(folder)


@pytest.fixture(scope="session")
def odd(spark, tmp_path_factory):
    documents = odd_documents()
    longest = documents[6][1].split()
    items = [(1, " ".join(longest[10:40]), "k"), (2, None, None), (3, "", None), (4, "few words", "k"), (None, " ".join(longest[60:90]), "k"), (6, "never seen. " + " ".join(f"v{k}" for k in range(30)), "k"), (1, " ".join(longest[10:40]), "k")]
    turns = [(c, t, r, f"{r} line {c} {t}\nmore text of it here?", "a", "b") for c in range(6) for t, r in enumerate(["system", "user", "assistant", "user", "assistant"][c % 2 :])]
    turns += [(7, 0, None, "no role"), (7, 1, "user", None), (None, 0, "user", "lost"), (8, None, "assistant", "where"), (7, 1, "user", None), (9, 0, "tool", "")]
    turns = [t if len(t) == 6 else (*t, None, None) for t in turns]
    return write(spark, tmp_path_factory.mktemp("odd"), documents, items, turns), documents


@pytest.fixture(scope="session")
def empty(spark, tmp_path_factory):
    return write(spark, tmp_path_factory.mktemp("empty"), [])
