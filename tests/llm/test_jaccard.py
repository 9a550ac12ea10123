"""Near copies of the pipeline's stage against all pairs."""

import random

import corpus_pipeline

SHINGLES = 900


def texts_of_pairs():
    """(id, text): pairs of 904 words whose last words differ, which sets their similarity; the last pair is just under 0.8."""
    rng = random.Random(7)
    out = []
    for k, differ in enumerate([100, 100, 98, 90, 80, 70, 60, 50, 40, 30, 25] * 6 + [101] * 6):
        words = [f"{rng.getrandbits(60):x}" for _ in range(SHINGLES + 4)]
        other = words[:-differ] + [f"{rng.getrandbits(60):x}" for _ in range(differ)]
        out += [(2 * k, " ".join(words)), (2 * k + 1, " ".join(other))]
    return out


def shingles(text):
    words = text.lower().split()
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))}


def test_stage_drops_pairs_at_least_as_similar_as_the_rule(spark):
    docs = texts_of_pairs()
    want = set()
    for (i, a), (j, b) in zip(docs[::2], docs[1::2], strict=True):
        x, y = shingles(a), shingles(b)
        want |= {i} if 5 * len(x & y) >= 4 * len(x | y) else {i, j}
    assert len(want) == 66 + 12
    left = corpus_pipeline.near_copies_stage(spark, spark.createDataFrame(docs, "doc_id long, text string"), "")
    assert {r.doc_id for r in left.collect()} == want


def test_groups_are_components_of_all_similar_pairs(spark):
    """A base and 120 variants of it: some pairs of variants are similar, others only by way of the base."""
    rng = random.Random(8)
    base = [f"b{k}" for k in range(400)]
    docs = []
    for k in range(120):
        words = list(base)
        for _ in range(rng.randint(2, 12)):
            words[rng.randrange(400)] = f"n{rng.getrandbits(40)}"
        docs.append((k, " ".join(words)))
    docs += [(500 + k, f"alone {k}") for k in range(5)] + [(600, ""), (601, " \n"), (602, "ALONE 1")]
    sets = {i: shingles(t) if t.split() else set() for i, t in docs}
    label = {i: i for i in sets}
    changed = True
    while changed:
        changed = False
        for i, x in sets.items():
            for j, y in sets.items():
                if 5 * len(x & y) >= 4 * len(x | y) and label[j] < label[i]:
                    label[i], changed = label[j], True
    left = corpus_pipeline.near_copies_stage(spark, spark.createDataFrame(docs, "doc_id long, text string"), "")
    assert {r.doc_id for r in left.collect()} == {i for i in sets if label[i] == i}


def test_blocks_of_a_large_cluster_give_the_same_groups(spark):
    from motifmill.llm.jaccard import near_copy_components

    rng = random.Random(9)
    base = [f"b{k}" for k in range(300)]
    docs = []
    for k in range(90):
        words = list(base)
        for _ in range(rng.randint(1, 9)):
            words[rng.randrange(300)] = f"n{rng.getrandbits(40)}"
        docs.append((k, " ".join(words)))
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    groups = [{(r.key, r.first.key) for r in near_copy_components(frame, block=b).collect()} for b in (10_000, 16)]
    assert groups[0] == groups[1] and len({g for _, g in groups[0]}) < 90


def test_repeated_ids_with_other_texts_are_judged_each(spark):
    words = lambda a, n: " ".join(f"{a}{k}" for k in range(n))
    docs = [(1, words("t", 40), "x"), (5, words("t", 40), "y"), (5, words("u", 40), "z"), (5, words("u", 40).upper(), "z"), (5, words("u", 40), "z"), (None, words("u", 40), "n"), (None, None, None), (1, words("v", 40), "w"), (9, None, "e"), (8, "", "f")]
    left = corpus_pipeline.near_copies_stage(spark, spark.createDataFrame(docs, "doc_id long, text string, first string"), "")
    assert left.columns == ["doc_id", "text", "first"]
    want = [(1, words("t", 40), "x"), (1, words("v", 40), "w"), (5, words("u", 40).upper(), "z"), (8, "", "f"), (None, None, None), (None, words("u", 40), "n")]
    assert sorted(map(repr, map(tuple, left.collect()))) == sorted(map(repr, want))
