"""The pipeline's near-dedup stage against brute-force Jaccard 0.8 pairs of five-word shingles."""

import corpus_pipeline as cp

from tests.conftest import SMOKE


def shingles(text):
    words = (text or "").split()
    words = [w.lower() if w.isascii() else w for w in words]
    return frozenset(tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))) if words else frozenset()


def brute_kept(rows):
    """Ids that are the smallest of their component over all pairs of Jaccard 0.8 and more."""
    sets, up = {i: shingles(t) for i, t in rows}, {i: i for i, _ in rows}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            x, y = sets[a], sets[b]
            if min(len(x), len(y)) >= 0.8 * max(len(x), len(y)) and len(x & y) >= 0.8 * len(x | y):
                ra, rb = root(a), root(b)
                up[max(ra, rb)] = min(ra, rb)
    return {i for i in ids if root(i) == i}


def test_stage_links_all_pairs_of_jaccard_08(spark):
    docs = spark.read.parquet(f"{SMOKE}/documents.parquet").select("doc_id", "text").dropDuplicates(["doc_id"])
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    base = " ".join(f"word{k}" for k in range(200))
    drift = [" ".join(f"x{k // 3}{j}" if k < 4 * j and k % 4 == 0 else f"word{k}" for k in range(200)) for j in range(8)]
    rows += [(10**6, base)] + [(10**6 + 1 + j, t) for j, t in enumerate(drift)] + [(2 * 10**6, "a b"), (2 * 10**6 + 1, "A  b")]
    kept = cp._without_near_duplicates(spark, spark.createDataFrame(rows, "doc_id bigint, text string"), SMOKE).toPandas()
    assert set(kept.doc_id) == brute_kept(rows)
