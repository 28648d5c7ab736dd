"""The pipeline, stage by stage, against brute force on each stage's own input."""

import re

import corpus_pipeline as cp
import pytest

from capmix.llm import toxicity
from capmix.llm.common import materialise
from tests.conftest import ORACLE, SMOKE
from tests.llm.test_llm import brute_redundant
from tests.llm.test_near_copies import brute_kept


@pytest.fixture(scope="module")
def stages(spark):
    """What each stage was given and returned, as pandas frames."""
    docs, out = spark.read.parquet(f"{ORACLE}/documents.parquet"), []
    for name, stage in cp.STAGES:
        done = materialise(stage(spark, docs, ORACLE), name)
        out.append((docs.toPandas(), done.toPandas()))
        docs = done
    return out


COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_columns_and_order(stages):
    assert [n for n, _ in cp.STAGES] == ["toxicity", "simhash_near_dedup", "suffix_array_dedup", "benchmark_decontamination", "best_fit_packing"]
    assert all(list(done.columns) == COLUMNS for _, done in stages[:-1])


def test_toxic_documents_go(spark, stages):
    given, kept = stages[0]
    lexicon = toxicity.train(spark.read.parquet(f"{ORACLE}/documents.parquet"), spark.read.parquet(f"{ORACLE}/labels.parquet"))
    bad = [i for i, t in zip(given.doc_id, given.text, strict=True) if (lambda w: lexicon.score(w[0], w[2]))(lexicon.weigh(toxicity.fold(t))) >= 0.5]
    assert set(given.doc_id) - set(kept.doc_id) == set(bad) and bad


def test_one_of_each_component_stays(stages):
    """Five-word Jaccard similarity of 0.8 and more, over all pairs: the rule of stages on word shingles."""
    given, kept = stages[1]
    want = brute_kept(list(zip(given.doc_id.tolist(), given.text.tolist(), strict=True)))
    assert set(kept.doc_id) == want and len(kept) == len(want)


def test_no_passage_repeats(stages):
    given, kept = stages[2]
    red = brute_redundant(given.text, given.doc_id)
    touched = {i for i, _ in red}
    before, after = given.set_index("doc_id").text, kept.set_index("doc_id").text
    assert all(after[i] == before[i] for i in before.index if i not in touched)
    for i in touched:
        words = before[i].split()
        left = [w for k, w in enumerate(words) if (i, k) not in red]
        assert (after[i].split() if i in after.index else []) == left


def test_contaminated_documents_go(spark, stages):
    """Every document, against windows looked up as tuples of words."""
    given, kept = stages[3]
    words = lambda t: re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    windows = {}
    for r in spark.read.parquet(f"{ORACLE}/benchmark.parquet").collect():
        w = words(r["text"])
        n = min(len(w), 13)
        for k in range(len(w) - n + 1 if w else 0):
            windows.setdefault(n, set()).add(tuple(w[k : k + n]))
    after = kept.set_index("doc_id").text
    cut = 0
    for i, t in zip(given.doc_id, given.text, strict=True):
        w, hit = words(t), set()
        for n, some in windows.items():
            hit.update(p for k in range(len(w) - n + 1) if tuple(w[k : k + n]) in some for p in range(k, k + n))
        bad = bool(hit) and 20 * len(hit) >= len(w)
        assert (i in after.index) == (not bad)
        if not bad:
            cut += bool(hit)
            assert (after[i] == t) if not hit else words(after[i]) == [x for k, x in enumerate(w) if k not in hit]
    assert len(kept) < len(given)


def test_bins_have_no_conflict(stages):
    given, packed = stages[4]
    m = packed.merge(given[["doc_id", "source", "text"]], on="doc_id")
    groups = m.groupby(["bin_group", "bin"])
    assert set(packed.doc_id) == set(given.doc_id) and groups["size"].sum().max() <= 4096
    assert (groups.source.nunique() == groups.size()).all() and (groups.text.nunique() == groups.size()).all()


PASSAGE = " ".join(f"p{k}" for k in range(60))
OTHER = " ".join(f"u{k}" for k in range(200))
WIDE = "doc_id bigint, text string, lang string, source string, n_chars bigint, _row int, row int, spans int, _spans int, n_hit int, score int, text_ int, id int, stays int, n int"


def odd(spark):
    rows = [
        (1, None, None, None, None), (1, None, None, None, None), (2, "", "en", "s", 0), (None, "only text", "en", "s", 9), (None, f"z {PASSAGE}", "en", "s", 9),
        (3, "word " * 20_000, "en", None, 1), (3, "word " * 20_000, "en", None, 1), (3, "word " * 20_000, "de", None, 1), (4, f"a b {PASSAGE} c", "en", "s", 1), (4, OTHER, "en", "s", 1), (4, "short text stays", "en", "s", 1),
        (5, OTHER + " more", "en", "s", 1),
    ]
    return spark.createDataFrame([(*r, *range(10)) for r in rows], WIDE)


def test_odd_rows_pass_every_stage(spark):
    """Nulls, equal ids with different texts, repeated rows, long texts and clashing names, stage by stage."""
    docs, want = odd(spark), set(WIDE.replace(" bigint", "").replace(" string", "").replace(" int", "").split(", "))
    toxic, near, cut, clean, packed = (stage(spark, docs, ORACLE) for _, stage in cp.STAGES)
    for done in (toxic, near, cut, clean):
        assert set(done.columns) == want and done.filter("_row = 0 AND row = 1 AND spans = 2 AND _spans = 3 AND n_hit = 4 AND score = 5 AND id = 7 AND stays = 8 AND n = 9").count() == done.count()
    assert toxic.count() == clean.count() == 12
    plain = lambda df: sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)
    assert plain(clean) == plain(toxic) == plain(docs)
    # null, empty and wordless texts are one group; equal rows stay once; rows that share an id are judged apart; of the
    # two near copies that hold the passage the one with an id stays
    got = plain(near)
    assert got == sorted([(1, None), (None, "only text"), (3, "word " * 20_000), (4, f"a b {PASSAGE} c"), (4, OTHER), (4, "short text stays")], key=str)
    assert [r["lang"] for r in near.filter("doc_id = 3").collect()] == ["de"]
    cut_texts = [t for _, t in plain(cut)]
    assert "a b  c" in cut_texts and f"z {PASSAGE}" in cut_texts and "short text stays" in cut_texts and OTHER in cut_texts and cut_texts.count(None) == 2
    assert sum(r["size"] for r in packed.filter("doc_id = 4").collect()) == 64 + 201 + 4
    for _, stage in cp.STAGES:
        assert stage(spark, docs.limit(0), ORACLE).count() == 0


def test_run_leaves_only_the_result(spark):
    import glob

    from capmix.llm.common import shared_folder

    before = set(glob.glob(shared_folder(spark).removeprefix("file://") + "/capmix/*"))
    assert cp.run(spark, SMOKE).count() > 0
    made = set(glob.glob(shared_folder(spark).removeprefix("file://") + "/capmix/*")) - before
    assert len(made) == 1 and "best_fit" in made.pop()
