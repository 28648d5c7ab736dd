"""The whole bigram and successor tables against brute force."""

from collections import Counter

from capmix.plans import caption_queries
from capmix.sources.tables import load
from tests.conftest import SMOKE


def test_whole_tables_have_rare_rows(spark):
    import re

    count = Counter()
    for r in load(spark, SMOKE, "documents").select("text").collect():
        for part in re.split(r"[.\n]", r["text"] or ""):
            words = re.findall(r"[^\W\d_]+", part.lower())
            if words:
                marked = ["<s>", *words, "</s>"]
                count.update(zip(marked, marked[1:], strict=False))
    queries = caption_queries.queries()
    got = {(r["w1"], r["w2"]): r["n"] for r in queries["cap_bigrams"](spark, SMOKE).collect()}
    assert got == dict(count) and min(count.values()) < 3
    want, after = set(), {}
    for (a, b), n in count.items():
        after.setdefault(a, []).append((-n, b.encode(), b))
    for a, rows in after.items():
        want |= {(a, b, -n, k + 1) for k, (n, _, b) in enumerate(sorted(rows)[:5])}
    assert {tuple(r) for r in queries["topk_successors"](spark, SMOKE).collect()} == want
