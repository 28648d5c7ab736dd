"""near_dups against brute force: families of drifting copies, and exact copies of short texts."""

import pytest

from capmix.operators import near_copies, prep


def _sets(texts):
    words = {i: t.split() for i, t in texts.items()}
    return {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, w in words.items()}


@pytest.mark.parametrize("block_rows", [512, 3])
def test_all_pairs_of_classes_and_copies_of_short_texts(spark, monkeypatch, block_rows):
    monkeypatch.setattr(near_copies.pairs, "__defaults__", (*near_copies.pairs.__defaults__[:-1], block_rows))

    def word(k, j=0):
        return "w" + "".join(chr(97 + int(c)) for c in f"{k}{j}")

    # The head (id 1) differs from each copy in two places, the copies from each other in one or two.
    texts = {1: " ".join(word(k) for k in range(100))}
    for j in range(2, 10):
        texts[j] = " ".join(word(k, 9 if k in (20, 50) else j if k == 5 * j else 0) for k in range(100))
    texts |= {20: "two words", 21: "two words", 22: "a b c d", 30: texts[3]}
    got = prep.near_duplicates(spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")).collect()
    sets, want = _sets(texts), {}
    reps = {i: min(j for j in sets if sets[j] == sets[i]) for i in sets}
    for a in sets:
        for b in sets:
            jaccard = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
            if a < b and jaccard >= 0.8 and (reps[b] == a or (reps[a] == a and reps[b] == b)):
                want[a, b] = jaccard
    assert {(r["a"], r["b"]): r["jaccard"] for r in got} == pytest.approx(want)
    assert len(got) == len(want) and (20, 21) in want and (3, 30) in want and (2, 3) in want and (1, 2) not in want
    members = prep.near_duplicate_members(spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")).collect()
    assert {r["doc_id"]: r["rep"] for r in members} == reps
