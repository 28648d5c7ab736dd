"""The ten operators against brute force, exact round trips, held-out accuracy and edge cases."""

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st

from capmix.llm import chat, components, decontamination, neighbours, packing, quality, queries, repeats, sharding, simhash, token_files, toxicity
from tests.conftest import ORACLE, SMOKE, rows

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def docs_of(spark, texts, ids=None):
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, t, "en", None if t is None else f"s{(i or 0) % 3}", 0) for i, t in zip(ids, texts, strict=True)], DOCS)


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{ORACLE}/documents.parquet").toPandas().sort_values("doc_id")


# Chat formatting

BYTE_BPE = queries.tokenizer_path("byte_bpe_50k.json")


@given(st.text(max_size=60) | st.sampled_from(["<|im_end|>", r"<|\im_start|>", r"<|\\endoftext|> <|im_sep|>", "<|<|im_end|>|>"]))
@settings(max_examples=150, deadline=None)
def test_escape_is_reversible(text):
    escaped = chat.escape(text)
    assert chat.unescape(escaped) == text
    assert not any(m in escaped for m in chat.MARKS)


def test_chat_round_trip_and_sql(spark, duck):
    got = queries.op1(spark, ORACLE).toPandas()
    want = duck.sql(queries.oracle_sql()["op1_chat_format"]).df()
    assert rows(got[list(want.columns)]) == rows(want)


def test_chat_edges(spark):
    data = [(1, 1, "assistant", None), (1, 0, "user", "q <|im_end|>"), (1, 0, "user", "q <|im_end|>"), (None, None, None, "x"), (2, 5, "assistant", "é" * 3000)]
    df = spark.createDataFrame(data, "conv_id bigint, turn bigint, role string, text string").withColumn("ids", chat.F.lit(1)).withColumn("mask", chat.F.lit(2))
    formatted = chat.format_chat(df, BYTE_BPE)
    got = {r["conv_id"]: r for r in chat.read_back(formatted, BYTE_BPE).collect()}
    assert (got[1]["n_turns"], got[1]["loss_chars"], got[2]["loss_chars"], got[None]["n_turns"]) == (3, 0, 3000, 1)
    text = "user\nq <|im_end|>\n" * 2 + "assistant\n\n"
    assert got[1]["turns_sha256"] == hashlib.sha256(text.encode()).hexdigest()
    tok = chat.tokenizer_at(BYTE_BPE)
    turns = sorted((r for r in formatted.collect() if r["conv_id"] == 1), key=lambda r: r["seq"])
    assert [r["token_start"] for r in turns] == list(np.cumsum([0] + [len(r["ids"]) for r in turns])[:-1])
    assert chat.render(turns[0]["ids"], tok) == r"<|im_start|>user<|im_sep|>q <|\im_end|><|im_end|>"
    assert chat.read_back(chat.format_chat(df.limit(0), BYTE_BPE), BYTE_BPE).count() == 0


# Nearest neighbours


def brute_neighbours(ids, x, step=20, top=20):
    scores = neighbours.exact_scores
    out = {}
    for q in [i for i in range(len(ids)) if ids[i] % step == 0]:
        s = scores(np.broadcast_to(x[q], x.shape), x)
        order = np.lexsort((ids, -s))
        out[int(ids[q])] = [(int(ids[k]), s[k]) for k in order if ids[k] != ids[q]][:top]
    return out


def test_neighbour_recall(spark):
    e = spark.read.parquet(f"{ORACLE}/embeddings.parquet").toPandas().sort_values("vec_id")
    want = brute_neighbours(e.vec_id.values, np.stack(e.embedding.values).astype(float))
    got = queries.op2(spark, ORACLE).toPandas()
    assert got.groupby("query_id").size().eq(20).all() and set(got.query_id) == set(want)
    hit = sum(len(set(g.vec_id) & {i for i, _ in want[q]}) for q, g in got.groupby("query_id"))
    assert hit / (20 * len(want)) >= 0.9
    exact = {(q, i): s for q, found in want.items() for i, s in found}
    assert all(exact[r.query_id, r.vec_id] == r.score for r in got.itertuples() if (r.query_id, r.vec_id) in exact)


def test_neighbour_edges(spark):
    rng = np.random.default_rng(1)
    data = [(k, rng.normal(size=8).tolist()) for k in range(60)]
    data += [(100 + k, data[0][1]) for k in range(50)]  # copies: ties go to smaller ids
    data += [(200, None), (201, [0.0] * 8), (202, [float("nan")] * 8), (203, [None] * 8), (204, []), (220, [1.0, 2.0]), (None, data[1][1])]
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<double>")
    got = neighbours.search(df, df.filter("vec_id % 20 = 0"), 20, recall=1.0, block_rows=16).toPandas()
    kept = [(i, v) for i, v in data if i is not None and (i < 60 or 100 <= i < 150)]
    want = brute_neighbours(np.array([i for i, _ in kept]), np.array([v for _, v in kept]))
    for q, g in got.groupby("query_id"):
        assert g.sort_values("rank").vec_id.tolist() == [i for i, _ in want[q]]
    assert set(got.query_id) == set(want)
    assert neighbours.search(df.limit(0), df.limit(0)).count() == 0
    few = neighbours.search(df.filter("vec_id < 3"), df.filter("vec_id = 0"), 20)
    assert few.count() == 2


def test_neighbours_are_exact_on_uneven_vectors(spark):
    """Tight groups that codes can't tell apart, lengths of many magnitudes, lists of less than 20 rows."""
    rng = np.random.default_rng(5)
    tight = rng.normal(size=(3, 16))[rng.integers(0, 3, 1500)] + 1e-3 * rng.normal(size=(1500, 16))
    uneven = rng.normal(size=(1500, 16)) * np.exp(2 * rng.normal(size=(1500, 1)))
    x = np.concatenate([tight, uneven]).astype(np.float32).astype(float)
    df = spark.createDataFrame([(k, v) for k, v in enumerate(x.tolist())], "vec_id bigint, embedding array<float>")
    for sample_rows in (8, 400, 8192):
        got = neighbours.search(df, df.filter("vec_id % 20 = 0"), 20, lists=40, sample_rows=sample_rows, block_rows=700).toPandas()
        found = {q: g.sort_values("rank") for q, g in got.groupby("query_id")}
        want = brute_neighbours(np.arange(len(x)), x)
        assert {q: list(zip(g.vec_id, g.score, strict=True)) for q, g in found.items()} == want


# Token files

WORD_BPE = queries.tokenizer_path("word_bpe_49k.json")
ODD = ["", None, "Hello, WORLD... it's 3.5\x1cx y\n\n", "é" * 5000, "a" * 20_000 + " <|endoftext|>  z", "é İstanbul ẞ Σσς", "don't,. ...,,x., y", "same", "same"]


def test_token_files_round_trip(spark, tmp_path):
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(WORD_BPE)
    df = docs_of(spark, ODD, [5, 3, 9, 1, 7, 2, None, 8, 8])
    token_files.write_tokens(df, str(tmp_path / "t"), WORD_BPE, 2)
    got = token_files.read_tokens(spark, str(tmp_path / "t")).collect()
    by_id = {}
    for i, t in zip([5, 3, 9, 1, 7, 2, None, 8, 8], ODD, strict=True):
        by_id.setdefault(i, []).append(plain.encode(t or "", add_special_tokens=False).ids + [2])
    assert sorted(map(str, ((r["id"], r["tokens"]) for r in got))) == sorted(map(str, ((i, t) for i, ts in by_id.items() for t in ts)))
    ordered = sorted(got, key=lambda r: r["start"])
    assert [r["id"] for r in ordered] == [None, 1, 2, 3, 5, 7, 8, 8, 9]
    assert [r["start"] for r in ordered] == list(np.cumsum([0] + [r["n_tokens"] for r in ordered])[:-1])
    one = token_files.read_tokens(spark, str(tmp_path / "t"), ids=[7]).collect()
    assert [(r["id"], r["start"]) for r in one] == [(r["id"], r["start"]) for r in ordered if r["id"] == 7]
    crc = {r["id"]: r["ids_crc32"] for r in token_files.read_tokens(spark, str(tmp_path / "t"), digest=True).collect()}
    assert crc[9] == zlib.crc32(np.array(by_id[9][0], "<u4").tobytes())
    token_files.write_tokens(df.limit(0), str(tmp_path / "e"), WORD_BPE, 2)
    assert token_files.read_tokens(spark, str(tmp_path / "e")).count() == 0


def test_token_query_equals_the_tokenizer(spark, documents):
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(WORD_BPE)
    ids = [np.array(e.ids + [2], "<u4") for e in plain.encode_batch(documents.text.fillna("").tolist(), add_special_tokens=False)]
    got = queries.op3(spark, ORACLE).toPandas().sort_values("doc_id")
    n = np.array([len(i) for i in ids])
    assert got.n_tokens.tolist() == n.tolist() and got.start.tolist() == (np.cumsum(n) - n).tolist()
    assert got.ids_crc32.tolist() == [zlib.crc32(i.tobytes()) for i in ids]


def test_block_needs_its_dictionary():
    block = token_files.pack_block([b"x"], 2, 12345)
    with pytest.raises(ValueError, match="dictionary"):
        token_files.Block(block, {})


# Decontamination


def brute_hits(text, items, window=13):
    words = lambda t: re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    w, hit, found = words(text), set(), set()
    for i, item in items:
        v = words(item)
        n = min(len(v), window)
        for k in range(len(v) - n + 1 if v else 0):
            for p in range(len(w) - n + 1):
                if w[p : p + n] == v[k : k + n]:
                    hit.update(range(p, p + n))
                    found.add(str(i))
    return len(w), len(hit), sorted(found)


def test_decontamination_brute_force(spark):
    rng = random.Random(5)
    vocabulary = ["a", "b", "É", "x1", "c"]
    text = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    items = [(1, text(20)), (2, text(5)), (3, text(13)), (4, None), (5, "..."), (6, "b"), (7, text(14)), (7, text(3))]
    texts = [text(rng.choice([0, 3, 40, 90])) for _ in range(30)] + [None, "", items[0][1].upper() + " tail", "zz " * 400 + items[2][1]]
    for size in (1 << 20, 20):  # the second deals the items to several automata
        got = decontamination.decontaminate(docs_of(spark, texts).withColumn("n_hit", decontamination.F.lit("clash")), spark.createDataFrame(items, "item_id bigint, text string"), max_bytes=size, keep=["doc_id"])
        for r in got.collect():
            n, hit, found = brute_hits(texts[r["doc_id"]], items)
            assert (r["n_words"], r["n_hit"], r["item_ids"]) == (n, hit, found)
            assert r["items_sha256"] == hashlib.sha256(",".join(found).encode()).hexdigest()
            assert r["contaminated"] == (hit > 0 and 20 * hit >= n)


def test_decontamination_sql_and_clean_text(spark, duck):
    got = queries.op4(spark, ORACLE).toPandas()
    want = duck.sql(queries.oracle_sql()["op4_decontaminate"]).df()
    assert rows(got) == rows(want)
    item = " ".join(f"w{k}" for k in range(15))
    texts = ["pad " * 400 + item + "! more", item]
    cleaned = decontamination.decontaminate(docs_of(spark, texts), spark.createDataFrame([(1, item)], "item_id bigint, text string"), clean=True).orderBy("doc_id").collect()
    assert cleaned[0]["clean_text"] == "pad " * 400 + "! more" and cleaned[1]["clean_text"] is None
    assert decontamination.decontaminate(docs_of(spark, texts).limit(0), spark.createDataFrame([], "item_id bigint, text string")).count() == 0


# Sharding


@given(st.integers(1, 3000), st.text(max_size=5), st.integers(1, 40))
@settings(max_examples=25, deadline=None)
def test_places_are_a_bijection(n, key, shards):
    places = [sharding.place_of(i, n, key, shards) for i in range(n)]
    assert len(set(places)) == n
    assert all(sharding.row_at(*p, n, key, shards) == i for i, p in enumerate(places))


@pytest.mark.parametrize("n", [1, 2, 3, 24, 25, 1000])
def test_shards_match_the_computed_place(spark, n):
    df = spark.range(n).selectExpr("id * 3 as doc_id", "if(id % 5 = 0, null, repeat('é', cast(id % 7 as int))) as text", "'x' as shard", "1 as size")
    got = sharding.shard(df, 24).orderBy("doc_id").collect()
    assert [(r["shard"], r["slot"]) for r in got] == [sharding.place_of(i, n, "capmix", 24) for i in range(n)]
    assert [r["size"] for r in got] == [8 if i % 5 == 0 else 8 + 2 * (i % 7) for i in range(n)]
    sizes = np.bincount([r["shard"] for r in got], minlength=24)
    assert sizes.max() - sizes.min() <= 1


def test_shard_edges(spark):
    got = sharding.shard(docs_of(spark, ["a", "a", None, "b"], [1, 1, None, None]), 3).collect()
    assert sorted((r["row_number"] for r in got)) == [0, 1, 2, 3]
    assert {r["text_crc32"] for r in got} == {zlib.crc32(b"a"), zlib.crc32(b"b"), 0}
    assert sharding.shard(docs_of(spark, ["a"]).limit(0), 3).count() == 0


def test_shard_sql(spark, duck):
    got = queries.op5(spark, ORACLE).toPandas()
    assert rows(got) == rows(duck.sql(queries.oracle_sql()["op5_shard"]).df())


# Repeated passages


def brute_redundant(texts, ids, n=50):
    seen, out = {}, set()
    for i, t in sorted(zip(ids, texts, strict=True), key=lambda x: x[0]):
        w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (t or "").encode()))
        for k in range(len(w) - n + 1):
            key = tuple(w[k : k + n])
            if seen.setdefault(key, (i, k)) != (i, k):
                out.update((i, p) for p in range(k, k + n))
    return out


def covered(df):
    return {(r["doc_id"], p) for r in df.collect() for p in range(r["start"], r["start"] + r["n_words"])}


@pytest.mark.parametrize(("chunk", "heavy"), [(200, 20_000), (10_000_000, 20_000), (200, 0), (10_000_000, 1)])
def test_repeats_brute_force(spark, chunk, heavy):
    rng = random.Random(2)
    word = lambda: f"w{rng.randrange(4000)}"
    passage = [word() for _ in range(70)]
    texts = []
    for k in range(25):
        body = [word() for _ in range(rng.choice([10, 80, 200]))]
        at = rng.randrange(len(body))
        texts.append(" ".join(body[:at] + (passage[rng.randrange(15) :] if k % 2 else []) + body[at:]))
    texts += [texts[3], texts[3].upper(), "x " * 300, None, "", "y"]
    got = covered(repeats.repeated_passages(docs_of(spark, texts).repartition(5, "doc_id"), chunk_words=chunk, heavy=heavy))
    assert got == brute_redundant(texts, range(len(texts)))


def test_repeats_query_brute_force(spark, documents):
    assert covered(queries.op6(spark, ORACLE)) == brute_redundant(documents.text, documents.doc_id)


def test_repeat_coverage_sql(spark, duck):
    got = queries.repeat_coverage(spark, ORACLE).toPandas()
    assert rows(got) == rows(duck.sql(queries.oracle_sql()["repeat_coverage"]).df())


def test_remove_repeats(spark):
    passage = " ".join(f"p{k}" for k in range(60))
    texts = [f"one {passage} end", f"two  {passage}\n tail", passage, "clean", None, ""]
    got = {r["doc_id"]: r["text"] for r in repeats.remove_repeats(docs_of(spark, texts)).collect()}
    assert got == {0: texts[0], 1: "two  \n tail", 3: "clean", 4: None, 5: ""}
    # rows that share an id, or have none, keep their own words
    other = " ".join(f"u{k}" for k in range(200))
    shared = [r["text"] for r in repeats.remove_repeats(docs_of(spark, [texts[0], texts[1], other, "short text stays", f"x {passage}", None], [1, 2, 2, 2, None, None])).collect()]
    assert sorted(map(str, shared)) == sorted(map(str, ["one  end", "two  \n tail", other, "short text stays", f"x {passage}", None]))
    clash = docs_of(spark, texts).selectExpr("doc_id", "text", "1 as _id", "2 as spans", "3 as row", "4 as row_key", "5 as id", "6 as own_key")
    assert repeats.remove_repeats(clash).filter("_id = 1 AND spans = 2 AND row = 3 AND row_key = 4 AND id = 5 AND own_key = 6").count() == 5
    same = docs_of(spark, [texts[0], texts[0]], [4, 4])
    assert [r["text"] for r in repeats.remove_repeats(same).collect()] == [texts[0]] * 2
    assert repeats.remove_repeats(docs_of(spark, texts).limit(0)).count() == 0


@given(st.lists(st.integers(0, 3), min_size=0, max_size=80))
@settings(max_examples=60, deadline=None)
def test_rolling_hash_equality(values):
    h = np.array([xxhash.xxh64_intdigest(bytes([v])) for v in values], np.uint64)
    r = repeats.rolling(h, 5)
    grams = [tuple(values[k : k + 5]) for k in range(len(values) - 4)]
    assert all((r[i] == r[j]) == (grams[i] == grams[j]) for i in range(len(grams)) for j in range(i))


def test_matches_are_maximal(spark):
    passage = " ".join(f"p{k}" for k in range(400))
    got = repeats.repeated_passages(docs_of(spark, [f"a b c {passage} d", f"e {passage} f g"])).collect()
    assert [(r["doc_id"], r["start"], r["n_words"], r["source_doc_id"], r["source_start"]) for r in got] == [(1, 1, 400, 0, 3)]


@given(st.lists(st.lists(st.integers(0, 2), max_size=60), min_size=2, max_size=5))
@settings(max_examples=60, deadline=None)
def test_compare_equals_brute_force(texts):
    size, anchor = 8, 3
    chunk = repeats._Chunk(size, anchor)
    for i, t in enumerate(texts):
        chunk.add(i, 0, " ".join(map(str, t)).encode())
    if not chunk.docs:
        return
    doc, row, at, low, high, base = chunk.flat()
    words = np.concatenate([d[2] for d in chunk.docs]).astype(np.uint32)
    s = repeats.Suffixes(chunk.anchors(), doc, row, at, low, high, repeats._around(words, base + at, low, high, size, size - anchor))
    i, o, j = repeats.compare(s, size)
    seen, want = {}, set()
    for d, t in enumerate(texts):
        for k in range(len(t) - size + 1):
            first = seen.setdefault(tuple(t[k : k + size]), (d, k))
            if first != (d, k):
                want.add((d, k, *first))
    assert {(int(s.doc[a]), int(s.at[a] + b), int(s.doc[c]), int(s.at[c] + b)) for a, b, c in zip(i, o, j, strict=True)} == want


# SimHash


def plain_fingerprint(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(" ".join(w[k : k + 3]).encode(), seed=42) for k in range(max(1, len(w) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(fps, ids, radius=2):
    root = list(range(len(fps)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i] ^ fps[j]).count("1") <= radius:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    least = {}
    for k in range(len(fps)):
        least[find(k)] = min(least.get(find(k), ids[k]), ids[k])
    return [least[find(k)] for k in range(len(fps))]


def test_simhash_query_brute_force(spark, documents):
    got = queries.op7(spark, ORACLE).toPandas().sort_values("doc_id")
    fps = [plain_fingerprint(t) for t in documents.text]
    assert [int(f, 16) for f in got.fingerprint] == fps
    assert got.component_id.tolist() == brute_components(fps, documents.doc_id.tolist())


@pytest.mark.parametrize("block_rows", [8, 100_000])
def test_links_of_dense_fingerprints(spark, block_rows):
    rng = random.Random(9)
    fps = set()
    for _ in range(6):
        base = rng.getrandbits(64)
        for _ in range(40):
            fps.add(base ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(4))))
    fps = sorted(f % (1 << 64) for f in fps)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = spark.createDataFrame([(f,) for f in signed], "fp bigint")
    roots = {r["node"]: r["root"] for r in components.components(simhash.links(df, 2, block_rows)).collect()}
    want = brute_components(fps, list(range(len(fps))))
    mine = [roots.get(s, s) for s in signed]
    assert len(set(mine)) == len(set(want))
    assert all((mine[i] == mine[j]) == (want[i] == want[j]) for i in range(len(fps)) for j in range(0, i, 7))


def test_components_of_chain_star_and_clique(spark):
    edges = [(k, k + 1) for k in range(200)] + [(1000, 1001 + k) for k in range(300)] + [(5000 + i, 5000 + j) for i in range(12) for j in range(i)] + [(7, 7)]
    got = components.components(spark.createDataFrame(edges, "a bigint, b bigint")).collect()
    assert len({r["root"] for r in got if r["node"] <= 200}) == 1 and len({r["root"] for r in got}) == 3 and len(got) == 201 + 301 + 12
    assert components.components(spark.createDataFrame([], "a bigint, b bigint")).count() == 0


def test_simhash_edges(spark):
    got = {r["id"]: r["component_id"] for r in simhash.near_duplicates(docs_of(spark, [None, "", "  \n", "a b", "A  B", "c"], [9, 4, 6, 3, 2, 8])).collect()}
    assert got == {9: 4, 4: 4, 6: 4, 3: 2, 2: 2, 8: 8}
    nulls = [(r["id"], r["component_id"]) for r in simhash.near_duplicates(docs_of(spark, ["q r s t", "q r s t", "z"], [None, 5, None])).collect()]
    assert sorted(nulls, key=str) == sorted([(None, 5), (5, 5), (None, None)], key=str)
    assert simhash.near_duplicates(docs_of(spark, ["a"]).limit(0)).count() == 0


# Packing


@given(st.lists(st.tuples(st.integers(1, 30), st.sampled_from([None, 1, 2, 3]), st.sampled_from([None, 7, 8, 9, 10])), max_size=60))
@settings(max_examples=60, deadline=None)
def test_pack_group_is_tightest_compatible(items):
    sizes, sources, clusters = ([x[k] for x in items] for k in range(3))
    got = packing.pack_group(list(range(len(items))), sizes, sources, clusters, 10)
    bins: dict[int, list] = {}
    for row, piece, start, size, which, offset in got:
        assert offset == sum(s for _, s in bins.get(which, []))
        fits = [(10 - sum(s for _, s in b), k) for k, b in bins.items() if 10 - sum(s for _, s in b) >= size and not any((sources[r] is not None and sources[r] == sources[row]) or (clusters[r] is not None and clusters[r] == clusters[row]) for r, _ in b)]
        if which in bins:
            assert 10 - sum(s for _, s in bins[which]) == min(fits)[0]
        elif size < 10:
            assert not fits
        bins.setdefault(which, []).append((row, size))
    packed = np.zeros(len(items), int)
    for row, _, _, size, _, _ in got:
        packed[row] += size
    assert packed.tolist() == sizes


def test_pack_query(spark, documents):
    got = queries.op8(spark, ORACLE).toPandas().merge(documents[["doc_id", "source", "text"]], on="doc_id")
    groups = got.groupby(["bin_group", "bin"])
    assert groups["size"].sum().max() <= packing.CAPACITY
    assert (groups.source.nunique() == groups.size()).all() and (groups.text.nunique() == groups.size()).all()
    sizes = got.groupby("doc_id")["size"].sum()
    assert sizes.to_dict() == {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) + 1 for i, t in zip(documents.doc_id, documents.text, strict=True)}


def test_pack_edges(spark):
    texts = ["w " * 10_000, "w " * 10_000, None, "", "a b"]
    got = packing.pack(docs_of(spark, texts, [1, 1, 2, None, 3]), capacity=1000).collect()
    assert sum(r["size"] for r in got if r["doc_id"] == 1) == 20_002
    assert {r["doc_id"] for r in got} == {1, 2, 3, None}
    assert packing.pack(docs_of(spark, texts).limit(0)).count() == 0


# Classifiers


def held_out_auc(got, labels, column):
    m = got.merge(labels, on="doc_id")
    m = m[m.held_out]
    pos, neg = m[m[column] == 1].score.values, m[m[column] == 0].score.values
    return float(np.mean([(p > neg).mean() + 0.5 * (p == neg).mean() for p in pos])), m


def test_quality_held_out(spark):
    labels = spark.read.parquet(f"{ORACLE}/labels.parquet").toPandas()
    got = queries.op9(spark, ORACLE).toPandas()
    assert got.held_out.tolist() == [zlib.crc32(str(i).encode()) % 3 == 1 for i in got.doc_id]
    auc, m = held_out_auc(got, labels, "quality")
    assert auc > 0.97 and (m.predicted == m.quality).mean() > 0.95


def test_toxicity_held_out(spark):
    labels = spark.read.parquet(f"{ORACLE}/labels.parquet").toPandas()
    got = queries.op10(spark, ORACLE).toPandas()
    assert got.held_out.tolist() == [zlib.crc32(str(i).encode()) % 5 == 0 for i in got.doc_id]
    auc, m = held_out_auc(got, labels, "toxic")
    assert auc > 0.75 and (m.predicted == m.toxic).mean() > 0.9


def test_folding_and_exceptions():
    lexicon = toxicity.Lexicon({" moron ": 5.0, " trash ": 4.0, " lowei": 3.0})
    weigh = lambda t: lexicon.weigh(toxicity.fold(t))[:2]
    assert weigh("you M0R0N!") == (5.0, 1) and weigh("mоrоn") == (5.0, 1) and weigh("mo​ron") == (5.0, 1)
    assert weigh("trash can") == (0.0, 0) and weigh("trash talk") == (4.0, 1)
    assert weigh("Loweich, xlowei") == (3.0, 1)
    assert weigh(None) == (0.0, 0) and weigh("") == (0.0, 0) and weigh("10 20") == (0.0, 0)


def test_classifier_edges(spark):
    docs = docs_of(spark, [None, "", "word " * 30_000, "a", "a"], [0, 1, 2, 3, 3])
    labels = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    for score, model in ((quality.score_quality, quality.train(docs, labels)), (toxicity.score_toxicity, toxicity.train(docs, labels))):
        got = score(docs.withColumn("score", quality.F.lit("clash")), model).collect()
        assert len(got) == 5 and all(r["score"] < 1e-6 and r["predicted"] == 0 for r in got)
        assert score(docs.limit(0), model).count() == 0
    some = spark.createDataFrame([(3, 1, 1), (3, None, None), (None, 1, 1)], "doc_id bigint, quality int, toxic int")
    assert {r["score"] for r in toxicity.score_toxicity(docs, toxicity.train(docs, some)).collect()} == {1.0}


def test_toxicity_hits_against_naive_matching(spark):
    """Aho-Corasick over the learned lexicon against a search for every entry at every word."""
    lexicon = toxicity.train(spark.read.parquet(f"{ORACLE}/documents.parquet"), spark.read.parquet(f"{ORACLE}/labels.parquet"))
    some = [e for e in lexicon.weights][:40] + [" aaa", " aa ", " b "]
    weights = {e: lexicon.weights.get(e, 1.5) for e in some}
    lexicon = toxicity.Lexicon(weights, ("aaa can", "clown car"))
    rng = random.Random(4)
    vocabulary = [e.strip() for e in some] + [e.strip() + "xx" for e in some[:9]] + ["aaa", "can", "clown", "car", "AA", "plain", "4aa", "b"]
    for _ in range(300):
        text = " ".join(rng.choice(vocabulary) for _ in range(rng.randrange(25)))
        folded = toxicity.fold(text).decode()
        best = {}
        for e, w in weights.items():
            for at in range(len(folded)):
                if folded.startswith(e, at):
                    best[at] = max(best.get(at, 0.0), w)
        for phrase in lexicon.exceptions:
            p = toxicity.fold(phrase).decode()
            for at in range(len(folded)):
                if folded.startswith(p, at):
                    best = {k: v for k, v in best.items() if not at <= k < at + len(p) - 1}  # the last space begins the next word
        total, hits, _ = lexicon.weigh(folded.encode())
        assert (round(total, 9), hits) == (round(sum(best.values()), 9), len(best))


def test_lexicon_has_no_cap(spark):
    """More entries than any former cap, and words of any length."""
    words = [f"zz{a}{b}{c}q" + "y" * (40 if a == "b" else 1) for a in "abcdefghijklmnopqrstuvwxyz" for b in "abcdefghijklmnopqrstuvwxyz" for c in "abcdefghij"]
    bad = [(" ".join(words[k::3]) + f" n{j}", 1) for k in range(3) for j in range(4)]
    good = [(" ".join(f"g{j}x{k}" for k in range(30)), 0) for j in range(400)]
    lexicon = toxicity.learn_lexicon(spark.createDataFrame([(t.encode(), y) for t, y in bad + good], "text binary, label int"))
    folded = toxicity.fold(" ".join(words))
    assert lexicon.weigh(folded)[1] == len(words)


def test_trees_against_plain_traversal_and_exhaustive_split():
    """Scores of flattened trees by walking each row, and the first split by trying every feature and threshold."""
    rng = np.random.default_rng(2)
    x = rng.integers(0, 12, (400, 5)).astype(float)
    y = ((x[:, 1] > 6) ^ (rng.random(400) < 0.1)).astype(float)
    trees = quality.fit_trees(x, y, rounds=12, depth=3)
    for row, got in zip(x[:60], trees.score(x[:60]), strict=True):
        raw = trees.bias
        for root in trees.roots.tolist():
            at = root
            while trees.left[at] != at:
                at = trees.left[at] if row[trees.feature[at]] <= trees.threshold[at] else trees.right[at]
            raw += trees.value[at]
        assert got == pytest.approx(1 / (1 + np.exp(-raw)))
    p = y.mean()
    g, h = y - p, np.full(len(y), p * (1 - p))
    gain = lambda m: g[m].sum() ** 2 / (h[m].sum() + 1.0) if m.any() else 0.0
    best = max(((gain(x[:, f] <= t) + gain(x[:, f] > t), f, t) for f in range(5) for t in np.unique(x[:, f]) if min((x[:, f] <= t).sum(), (x[:, f] > t).sum()) >= 8), key=lambda b: b[0])
    root = trees.roots[0]
    assert trees.feature[root] == best[1] and ((x[:, best[1]] <= trees.threshold[root]) == (x[:, best[1]] <= best[2])).all()


def test_quality_query_against_plain_statistics(spark, documents):
    """The query's scores from statistics counted word by word and trees walked row by row."""
    trees = quality.train(spark.read.parquet(f"{ORACLE}/documents.parquet"), spark.read.parquet(f"{ORACLE}/labels.parquet"))
    got = queries.op9(spark, ORACLE).toPandas().set_index("doc_id")
    for i, t in zip(documents.doc_id[:80], documents.text[:80], strict=True):
        raw, words = (t or "").encode(), (t or "").encode().split()
        own = dict(zip(quality.STATISTICS, quality.statistics(raw), strict=True))
        assert own["digits"] == pytest.approx(sum(48 <= b < 58 for b in raw) / max(len(raw), 1)) and own["distinct_words"] == pytest.approx(len(set(words)) / max(len(words), 1))
        assert got.loc[i, "score"] == pytest.approx(float(trees.score(np.array([list(own.values())]))[0]))


# Encoding, stored formats and hot keys


@given(st.lists(st.text(alphabet=st.sampled_from("aBé\u00c9İıʼn\u0301\u093c\u095bש\ufb2a'.,-<|>endoftx 1½\x1c\x1f\x00\x85\xa0\u2000\u200b\u3000Σσς\u212a\u1fef\n\t"), max_size=24) | st.text(max_size=12), max_size=8))
@settings(max_examples=400, deadline=None)
def test_encoder_equals_whole_texts(texts):
    import pyarrow as pa
    from array import array
    from tokenizers import Tokenizer

    enc = token_files.encoder(WORD_BPE, None)
    whole = _PLAIN.setdefault(0, Tokenizer.from_file(WORD_BPE)).encode_batch(texts, add_special_tokens=False)
    assert enc(pa.array(texts, pa.string())) == [array(enc.code, e.ids).tobytes() for e in whole]


_PLAIN: dict = {}


def test_only_a_word_splitter_is_encoded_by_words():
    import json

    spec = json.load(open(WORD_BPE, encoding="utf-8"))
    assert token_files.word_splitter(spec) and not token_files.encoder(BYTE_BPE, None).splits
    for change in ({"normalizer": None}, {"pre_tokenizer": None}, {"added_tokens": [spec["added_tokens"][0] | {"lstrip": True}]}, {"added_tokens": [spec["added_tokens"][0] | {"content": "abc."}]}, {"model": {"type": "WordPiece"}}):
        assert not token_files.word_splitter(spec | change)


def test_both_chat_encoders_give_the_same_ids():
    tok = chat.tokenizer_at(BYTE_BPE)
    texts = ["", "a b  c\n\n x", "é" * 300, " " * 30_000 + "x", "\t\n " * 9000, "don't <|endoftext|> 12", "日本 ½"]
    assert tok.ranks is not None and tok.encode(texts) == [e.ids for e in tok.tokenizer.encode_batch(texts, add_special_tokens=False)]
    assert tok.decode(tok.encode(texts)) == texts


def test_stored_chat_is_read_back_in_any_order(spark, tmp_path):
    data = [(c, t, "user" if t % 2 else "assistant", f"c{c} t{t} <|im_end|>") for c in range(100) for t in range(9)]
    formatted = chat.format_chat(spark.createDataFrame(data, "conv_id bigint, turn bigint, role string, text string"), BYTE_BPE)
    want = {tuple(r) for r in chat.read_back(formatted, BYTE_BPE, in_order=True).collect()}
    formatted.orderBy("seq", chat.F.desc("conv_id")).repartition(7).write.parquet(str(tmp_path / "chat"))
    stored = spark.read.parquet(str(tmp_path / "chat"))
    assert {tuple(r) for r in chat.read_back(stored, BYTE_BPE).collect()} == want and len(want) == 100
    with pytest.raises(Exception, match="in order of seq"):
        chat.read_back(stored, BYTE_BPE, in_order=True).collect()


def test_decontamination_coverage_and_clashing_names(spark):
    item = " ".join(f"w{k}" for k in range(4))
    docs = docs_of(spark, [f"{item} a b c d e f", "x " * 10, None]).withColumns({c: decontamination.F.lit(1) for c in ("_n", "_spans", "_items", "_text", "row", "n", "spans", "items", "N_HIT")})
    bench = spark.createDataFrame([(1, item)], "item_id bigint, text string")
    judge = lambda **k: {r["doc_id"]: r["contaminated"] for r in decontamination.decontaminate(docs, bench, **k).collect()}
    assert judge(coverage=0.4) == {0: True, 1: False, 2: False} and judge(coverage=0.41)[0] is False and judge(coverage=0)[0] is True
    got = decontamination.decontaminate(docs, bench, clean=True)
    assert {"_n", "_spans", "_items", "_text", "row", "n", "spans", "items"} <= set(got.columns) and got.count() == 3


@given(st.lists(st.lists(st.integers(0, 2), max_size=30), max_size=6), st.lists(st.integers(0, 3), max_size=60))
@settings(max_examples=120, deadline=None)
def test_automaton_against_brute_force(items, words):
    spell = lambda w: " ".join(f"w{x}" for x in w)
    texts = [(k, spell(w)) for k, w in enumerate(items)]
    automaton = decontamination.Automaton([(k, t.encode()) for k, t in texts], 5)
    spans, found = automaton.scan([f"w{x}".encode() for x in words])
    n, hit, ids = brute_hits(spell(words), texts, 5)
    covered_ = {p for a, b in spans.tolist() for p in range(a, b)}
    assert (len(covered_), sorted(str(k) for k in found)) == (hit, ids)


def test_repetitive_texts_are_scanned_in_linear_time():
    import time

    automaton = decontamination.Automaton([(1, b"a " * 60_000), (2, b"a a a")])
    begun = time.perf_counter()
    spans, found = automaton.scan([b"a"] * 60_000)
    assert found == {0, 1} and len(spans) and time.perf_counter() - begun < 5


def test_hot_ids_and_rows_are_numbered_in_parts(spark):
    rows_ = [(None if k % 3 else k, f"t{k % 50}") for k in range(900)] + [(7, "same")] * 300
    df = spark.createDataFrame(rows_, "doc_id bigint, text string")
    got = sharding.shard(df, 24, range_rows=20, same_rows=40).collect()
    assert sorted(r["row_number"] for r in got) == list(range(1200))
    assert all((r["shard"], r["slot"]) == sharding.place_of(r["row_number"], 1200, "capmix", 24) for r in got)
    assert sorted(map(str, ((r["doc_id"], r["text_crc32"]) for r in got))) == sorted(map(str, ((i, zlib.crc32(t.encode())) for i, t in rows_)))


def test_identical_rows_are_packed_in_several_groups(spark):
    df = docs_of(spark, ["same words here"] * 200 + [f"other {k}" for k in range(50)], [5] * 200 + list(range(50)))
    got = packing.pack(df, capacity=100, group_rows=32).toPandas()
    assert len(got) == 250 and got[got.doc_id == 5].bin_group.nunique() > 3
    assert (got[(got.doc_id == 5) & (got["size"] == 4)].groupby(["bin_group", "bin"]).size() == 1).all()


def test_masks_of_many_fingerprints():
    import itertools

    for n in (10, 10**6, 10**9, 10**13):
        masks = simhash.band_masks(n, 2)
        for a, b in itertools.combinations(range(0, 64, 5), 2):
            assert any(m >> a & 1 == 0 and m >> b & 1 == 0 for m in masks)
        assert n >> min(bin(m).count("1") for m in masks) <= 8


def test_trees_learn_an_interaction():
    rng = np.random.default_rng(0)
    x = rng.random((3000, 4))
    y = ((x[:, 0] > 0.5) & (x[:, 2] < 0.4)).astype(float)
    trees = quality.fit_trees(x, y, rounds=30)
    assert (trees.score(x) > 0.5).astype(float).__eq__(y).mean() > 0.98


# Every query runs on the smallest tables with a stable schema


@pytest.mark.parametrize("name", [n for n in queries.queries() if n != "pipeline"])
def test_queries_run(spark, name):
    got = queries.queries()[name](spark, SMOKE)
    assert got.count() > 0 and "void" not in dict(got.dtypes).values()
