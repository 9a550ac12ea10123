"""The pipeline's near copies: what the Gray tree finds, and how many links large clusters make."""

import random

from motifmill.llm import jaccard


def variants(count, words, most, seed):
    rng = random.Random(seed)
    base = [f"b{k}" for k in range(words)]
    docs = []
    for k in range(count):
        own = list(base)
        for _ in range(rng.randint(0, most)):
            own[rng.randrange(words)] = f"n{rng.getrandbits(40)}"
        docs.append((k, " ".join(own)))
    return docs


def test_copies_within_three_bits_are_found_by_the_gray_tree(spark, monkeypatch):
    """Without the keys of minima, the tree alone brings these together."""

    def nothing(batches):
        for batch in batches:
            yield batch.slice(0, 0).rename_columns(["u", "v"])

    monkeypatch.setattr(jaccard, "_bucket_links", nothing)
    rng = random.Random(5)
    docs = []
    for k in range(20):
        words = [f"{rng.getrandbits(60):x}" for _ in range(4000)]
        docs += [(2 * k, " ".join(words)), (2 * k + 1, " ".join([*words[:-1], "other"]))]
    groups = {(r.key, r.first.key) for r in jaccard.near_copy_components(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert groups == {(k, k - k % 2) for k in range(40)}


def test_links_of_a_large_cluster_grow_with_it_and_not_with_its_square(spark, monkeypatch):
    made = []
    inner = jaccard._meet

    def counted(*args):
        links = jaccard.materialise(inner(*args), "test-links")
        made.append(links.count())
        return links

    monkeypatch.setattr(jaccard, "_meet", counted)
    frame = spark.createDataFrame(variants(160, 300, 9, 4), "doc_id long, text string")
    whole = {(r.key, r.first.key) for r in jaccard.near_copy_components(frame, block=10_000).collect()}
    made.clear()
    parted = {(r.key, r.first.key) for r in jaccard.near_copy_components(frame, block=8).collect()}
    assert parted == whole
    assert len(made) == 2 and made[0] <= 160 + 20 * jaccard.PIVOTS
    assert made[1] <= 160


def test_cross_links_join_groups_of_similar_sets_only():
    import numpy as np

    sets = [np.arange(a, a + 100, dtype=np.uint64) for a in (0, 5, 10, 500, 505, 900)]
    assert jaccard.cross_links(sets, [1, 1, 2, 7, 8, 9], [False, False, True, True, True, True]) == [(2, 1), (8, 7)]
    assert jaccard.cross_links(sets, [1] * 6, [True] * 6) == []
