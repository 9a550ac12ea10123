"""The pivot walk of decontamination looks up single entries without array calls, which cost most of its time."""

import numpy as np

from motifmill.llm import decontaminate as D


def test_walk_makes_no_array_searches(monkeypatch):
    index = D.BlockMaxIndex([(k, " ".join(f"w{(7 * k + j) % 50}" for j in range(20))) for k in range(40)])
    terms = [index.terms[f"w{j}"] for j in range(20)]
    score = np.zeros(40)
    for t in terms:
        a, b = index.first[t], index.first[t + 1]
        score[index.item[a:b]] += index.weight[a:b]
    searches = []
    inner = np.searchsorted
    monkeypatch.setattr(np, "searchsorted", lambda *x, **y: searches.append(1) or inner(*x, **y))
    found = index.walk(terms)
    assert not searches
    assert [i for i, _ in found] == np.flatnonzero(score >= 1).tolist() and found
    assert all(abs(s - score[i]) < 1e-9 for i, s in found)
