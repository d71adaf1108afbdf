"""Each operator against a brute-force version, and its edge cases: nulls, empty and very long texts, repeated rows, empty tables, clashing columns."""

import collections
import hashlib
import random
import zlib

import numpy as np
import pytest

pytest.importorskip("seedcluster.llm")

from seedcluster.llm import bpe, components, debruijn, embed, html_blocks, merkle, minhash, packing, repair, repeats, tokens, toxicity  # noqa: E402
from seedcluster.llm.common import table  # noqa: E402

TIK, HF = tokens.tokenizer_path("byte_bpe_50k.tiktoken"), tokens.tokenizer_path("byte_bpe_50k.json")
SCHEMA = "doc_id long, text string, key long, g long, rep long, u long"


def words(r, n):
    return " ".join(r.choice("alpha beta gamma delta omega kappa été Straße one two".split()) + str(r.randrange(60)) for _ in range(n))


def fixture():
    """Texts with copies, near copies, shared passages, nulls, blanks, one very long one."""
    r = random.Random(4)
    base, passage = words(r, 200), words(r, 90)
    texts = [base, base, base.replace("alpha", "Alpha"), base + " tail end here now", words(r, 120) + " " + passage, passage + " " + words(r, 60), None, "", "   \n\t ", "one", "one two three", words(r, 6000), words(r, 40) + "\n\n" + passage, "it's ''s don't  we'll\n\n x"]
    near = base.split()
    near[50] = "changed"
    texts.append(" ".join(near))
    return list(enumerate(texts))


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, 1, 2, 3, 4) for i, t in fixture()], SCHEMA).repartition(3)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def shingles(text, k):
    w = (text or "").encode().lower().split()
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def reach(ids, links):
    up = {i: i for i in ids}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}


@pytest.mark.parametrize("source", ["fixture", "table"])
def test_minhash(spark, docs, sf_dir, source):
    df = docs if source == "fixture" else table(spark, sf_dir, "documents")
    sets = {x["doc_id"]: shingles(x["text"], 4) for x in df.collect()}
    links = [(a, b) for a in sets for b in sets if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    want = reach(sets, links)
    got = {x["doc_id"]: x for x in minhash.near_duplicates(df, width=4).collect()}
    assert {i: (x["n_shingles"], x["component_id"], x["kept"]) for i, x in got.items()} == {i: (len(s), want[i], want[i] == i) for i, s in sets.items()}


def test_components_of_a_long_path(spark):
    pairs = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (7, 7)]
    got = {x["node"]: x["component"] for x in components.components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100}


def test_bpe(docs):
    e = tokens.Encoder("tiktoken", TIK)
    want = {}
    for i, t in fixture():
        ids = e.tool.encode_ordinary(t or "")
        want[i] = (i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())
    for ways in ({}, {"long_chars": 900, "chunk_chars": 300, "overlap": 20}, {"chunk": 40, "shared": 8}):
        rows = bpe.encode_and_decode(docs, TIK, **ways).collect()
        assert {x["doc_id"]: tuple(x)[:4] for x in rows} == want
        assert max(x["n_chunks"] for x in rows) > 10
    assert bpe.decode(e.tool.encode_ordinary("naïve 中文"), TIK).decode() == "naïve 中文"


def test_pretokens_in_chunks():
    r = random.Random(2)
    for library, path in (("tiktoken", TIK), ("tokenizers", HF)):
        e = tokens.Encoder(library, path)
        for _ in range(60):
            t = "".join(r.choice(" \n\t  ''stredvml aA1,!ñ中 \x1c\x85😀") for _ in range(r.randint(0, 200))) + "a" * r.randint(0, 80)
            p = np.frombuffer(t.encode("utf-32-le"), np.uint32)
            two = np.array([0, len(p) // 3, len(p) // 3, len(p)])
            assert (tokens.rows_in_chunks(p, two, e.table, 16, 4)[0] == tokens.pretokens(p, two, e.table)).all() or not len(p)
            assert (tokens.chunked_pretokens(p, e.table, 16, 4) == tokens.pretokens(p, np.array([0, len(p)]), e.table)).all()
            ids, _ = e.encode(p, np.array([0, len(p)]))
            assert list(ids) == list(e.tool.encode_ordinary(t) if library == "tiktoken" else e.tool.encode(t, add_special_tokens=False).ids)


def test_toxicity(spark, sf_dir):
    r = random.Random(1)
    rows = [(i, words(r, 30) + (" you awful gremlin" if i % 4 == 0 else ""), int(i % 4 == 0)) for i in range(400)]
    df, labels = spark.createDataFrame([x[:2] for x in rows] + [(1000, None), (1001, "")], "doc_id long, text string"), spark.createDataFrame([(i, y, None) for i, _, y in rows], "doc_id long, toxic int, quality int")
    model = toxicity.fit(df, labels)
    got = {x["doc_id"]: x for x in toxicity.scored(df, model).collect()}
    held = [(got[i], y) for i, _, y in rows if toxicity.is_held_out(i)]
    assert len(got) == 402 and np.mean([x["predicted"] == y for x, y in held]) > 0.97
    w, _ = model
    moved = [abs(w[toxicity.word_features(x)].sum()) for kind in toxicity.IDENTITY for x in kind]
    assert max(moved) < 0.5
    assert toxicity.scored(empty(spark), toxicity.fit(empty(spark), labels.limit(0))).count() == 0


def test_counterfactual_lowers_bias():
    """Identity terms that go with label 1 in training move scores less with the penalty than without."""
    rng = np.random.default_rng(0)
    texts, labels = [], []
    bad, term = toxicity.word_features("gremlin"), toxicity.word_features("muslims")
    for i in range(600):
        y = i % 2
        t = [rng.integers(0, 1 << 18, 8)] + ([bad] if y else []) + ([term] if (y and i % 3) or i % 17 == 0 else [])
        texts.append(np.unique(np.concatenate(t)))
        labels.append(y)
    with_it, _ = toxicity.train(texts, np.array(labels, float), counterfactual=3.0)
    without, _ = toxicity.train(texts, np.array(labels, float), counterfactual=0.0)
    assert abs(with_it[term].sum()) < 0.6 * abs(without[term].sum())


def test_toxicity_penalty_labels_and_repeated_rows(spark):
    """The penalty changes scores of texts that name groups; null and conflicting labels and those of held-out rows change none; a longer word is no identity term."""
    r = random.Random(3)
    rows = [(i, words(r, 20) + (" gremlin" if i % 2 and i % 8 != 1 else "") + (" muslims" if i % 2 and i % 3 else ""), i % 2) for i in range(400)]
    df = spark.createDataFrame([x[:2] for x in rows] + [rows[5][:2], (9000, "they are muslims"), (9001, "they are people")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows], "doc_id long, toxic int")
    score = lambda m: {x["doc_id"]: x["score"] for x in toxicity.scored(df, m).collect()}
    strong, none = score(toxicity.fit(df, labels, counterfactual=20.0)), score(toxicity.fit(df, labels, counterfactual=0.0))
    assert strong[9000] - strong[9001] < 0.5 * (none[9000] - none[9001])
    flipped = spark.createDataFrame([(i, 1 - y if toxicity.is_held_out(i) else y) for i, _, y in rows] + [(9000, None), (9001, 0), (9001, 1)], "doc_id long, toxic int")
    assert score(toxicity.fit(df, flipped)) == score(toxicity.fit(df, labels))
    assert toxicity.scored(df, toxicity.fit(df, labels)).count() == df.count()
    for term, longer in (("white", "whitespace"), ("women", "womenfolk"), ("christians", "christmas")):
        assert toxicity.word_key(term) in toxicity.word_features(term) and toxicity.word_key(term) not in toxicity.word_features(longer)


def test_merkle(docs):
    rows = fixture()
    got = {x["doc_id"]: x for x in merkle.edited_against_next(docs).collect()}
    for k, (i, t) in enumerate(rows):
        a, b = t or "", rows[(k + 1) % len(rows)][1] or ""
        edit = a[: len(a) - len(a) // 2] + b[: len(a) // 2]
        x = got[i]
        assert (x["n_chars"], x["edited_sha256"], x["fingerprint"], x["edited_fingerprint"]) == (len(a), hashlib.sha256(edit.encode()).hexdigest(), merkle.fingerprint(a), merkle.fingerprint(edit))
        assert (x["near_next"] == 1.0) == (a == b)
    assert merkle.edited("a b c\nd e f\n" * 9, "a b c\nd e f\n" * 9) == []
    spans = merkle.edited(words(random.Random(1), 300), words(random.Random(1), 300)[:-3] + "xyz")
    assert spans and sum(e - s for s, e in spans) < 400


@pytest.mark.parametrize("by_words", [True, False])
@pytest.mark.parametrize("source", ["fixture", "table"])
def test_repeated_spans(spark, docs, sf_dir, by_words, source):
    df = docs if source == "fixture" else table(spark, sf_dir, "documents")
    seq = {x["doc_id"]: (x["text"] or "").encode().split() if by_words else (x["text"] or "").encode() for x in df.collect()}
    first = {}
    for i in sorted(seq):
        for j in range(len(seq[i]) - 49):
            first.setdefault(tuple(seq[i][j : j + 50]), i)
    got = {x["doc_id"]: tuple(x) for x in (debruijn.without_repeated_words if by_words else repeats.without_repeated_bytes)(df).collect()}
    for i, s in seq.items():
        gone = [False] * len(s)
        for j in range(len(s) - 49):
            if first[tuple(s[j : j + 50])] < i:
                gone[j : j + 50] = [True] * 50
        kept = [x for x, g in zip(s, gone, strict=True) if not g]
        spans = sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone))
        want = (i, len(s), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest()) if by_words else (i, len(s), sum(gone), spans, hashlib.sha256(bytes(kept)).hexdigest())
        assert got[i] == want


def test_unitigs():
    """Chains through unary nodes, a branch, and a ring, as edges between numbered nodes."""
    left, right = np.array([1, 2, 3, 10, 11, 3, 20, 21], np.uint64), np.array([2, 3, 4, 11, 12, 5, 21, 20], np.uint64)
    top, place, last = debruijn.unitigs(left, right)
    assert top.tolist() == [0, 0, 2, 3, 3, 5, 6, 7] and place.tolist() == [0, 1, 0, 0, 1, 0, 0, 0]
    assert last.tolist() == [1, 1, 2, 4, 4, 5, 6, 7]


def test_compaction_by_joins(spark):
    """A chain of five unitigs is one path with places; a node of two ways in parts paths; a ring stays apart."""
    rows = [(i, 10 * (i + 1), 100 + i, 101 + i) for i in range(5)] + [(20, 1, 300, 302), (21, 1, 301, 302), (22, 1, 302, 303), (30, 4, 400, 401), (31, 4, 401, 400), (40, 2, 500, 500)]
    found = spark.createDataFrame(rows, "uid long, n long, first long, last long")
    got = {x["uid"]: (x["path"], x["shift"]) for x in debruijn.compacted(found).collect()}
    assert [got[i] for i in range(5)] == [(0, 0), (0, 10), (0, 30), (0, 60), (0, 100)]
    assert all(got[i] == (i, 0) for i in (20, 21, 22, 30, 31, 40))


def test_long_copy_is_one_verified_span(spark, monkeypatch):
    """A passage of many names is verified as one span, and one whose source says otherwise is not removed."""
    r = random.Random(9)
    passage = " ".join(f"w{r.randrange(10**6)}" for _ in range(700))
    df = spark.createDataFrame([(1, "a b c " + passage), (2, "x y " + passage.replace(" ", "  \n"))], "doc_id long, text string")
    seen = spark.sparkContext.accumulator(0)

    def finish(t, row, start, length):
        seen.add(len(row))
        return debruijn.pa.table([debruijn._ids(t), debruijn.pa.array(np.full(len(t.ids), int(length.sum())))], ["doc_id", "n"])

    rows = {x["doc_id"]: x["n"] for x in debruijn.repeated_word_spans(df, 50, 16, finish, "doc_id long, n long").collect()}
    assert rows[2] == 651 and seen.value == 1
    ok = debruijn.repeated_word_spans(df, 50, 16, finish, "doc_id long, n long")
    assert ok.count() == 2


def test_suffix_owners():
    r = np.random.default_rng(0)
    for _ in range(40):
        t = np.tile(r.integers(97, 99, 60).astype(np.uint8), 12)[: r.integers(55, 700)].copy()
        t[r.integers(0, len(t), 3)] = 120
        at = np.flatnonzero(r.random(len(t) - 49) < 0.6)
        own = r.integers(0, 50, len(at))
        least = collections.defaultdict(lambda: 99)
        for a, o in zip(at, own, strict=True):
            least[t[a : a + 50].tobytes()] = min(least[t[a : a + 50].tobytes()], o)
        assert [least[t[a : a + 50].tobytes()] for a in at] == repeats.suffix_owners(t, at, own).tolist()


def test_embeddings(spark):
    r = np.random.default_rng(1)
    v = r.normal(size=(60, 16))
    v[20:40] = v[0] + 0.02 * r.normal(size=(20, 16))
    v[41] = v[40]
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(60, None), (61, [0.0] * 16), (62, [float("nan")] * 16), (63, [None] * 16), (64, v[40].tolist())]
    got = {x["vec_id"]: x for x in embed.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), 0.95, block=8).collect()}
    good = [(i, np.array(x)) for i, x in rows if i not in (60, 61, 62, 63)]
    links = [(a, b) for a, x in good for b, y in good if a < b and x @ y / np.sqrt((x @ x) * (y @ y)) >= 0.95]
    comp, n = reach([i for i, _ in rows], links), collections.Counter(i for p in links for i in p)
    assert {i: (x["n_links"], x["component_id"], x["kept"]) for i, x in got.items()} == {i: (n[i], comp[i], comp[i] == i) for i, _ in rows}


def ids_of(end):
    t = tokens.Encoder("tokenizers", HF).tool
    return {i: np.array(t.encode(x or "", add_special_tokens=False).ids + [end], "<u4") for i, x in fixture()}


def test_embeddings_edge_cases(spark):
    """Repeated rows are vectors of their own, null ids and odd vectors link with nothing else, clashing columns go, ties at the least id."""
    rows = [(1, [1.0, 0.0], 7, 8), (1, [1.0, 0.0], 7, 8), (2, [2.0, 0.0], 7, 8), (3, [0.0, 0.0], 7, 8), (4, None, 7, 8), (5, [1.0, None], 7, 8), (6, [float("nan"), 1.0], 7, 8), (9, [1.0, 0.0, 0.0], 7, 8)]
    got = sorted((x["vec_id"], x["n_links"], x["component_id"], x["kept"]) for x in embed.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>, n long, rep long")).collect())
    assert got == [(1, 2, 1, True), (1, 2, 1, True), (2, 2, 1, False), *((i, 0, i, True) for i in (3, 4, 5, 6, 9))]


def test_hub_of_links(spark):
    """A star and a chain of stars come together though one node has most links."""
    pairs = [(0, i) for i in range(1, 400)] + [(399, i) for i in range(1000, 1200)] + [(5000, 5001)]
    got = {x["node"]: x["component"] for x in components.components(spark.createDataFrame(pairs, "u long, v long")).collect()}
    assert all(c == 0 for n, c in got.items() if n < 5000) and got[5001] == 5000 and len(got) == 602


def test_toxicity_edge_cases(spark):
    """Null ids, clashing columns, very long and repeated texts are scored each."""
    r = random.Random(8)
    rows = [(i, words(r, 20) + (" gremlin" if i % 3 == 0 else ""), 1, 0.5) for i in range(120)]
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(120)], "doc_id long, toxic int")
    more = [(None, "x", 1, 0.5), (4, "gremlin " * 200_000, 1, 0.5), (4, rows[4][1], 1, 0.5)]
    df = spark.createDataFrame(rows + more, "doc_id long, text string, label int, score double")
    model = toxicity.fit(df, labels)
    got = toxicity.scored(df, model).collect()
    assert len(got) == 123 and all(0 <= x["score"] <= 1 and x["predicted"] == int(x["score"] >= 0.7) for x in got)
    kept = toxicity.without_toxic(df, model)
    assert kept.columns == df.columns and kept.count() == sum(x["predicted"] == 0 for x in got)


def test_merkle_against_plain_python(docs):
    """Likeness to the edited and the next text, from leaves cut and counted without the tree's walk."""
    from seedcluster.llm.common import CODES, spans_hash, word_spans

    def leaves(t):
        raw = np.frombuffer(t.encode(), np.uint8)
        s, e, _ = word_spans(raw, np.array([0, len(raw)]))
        cuts = sorted({int(x) for x, h in zip(e, spans_hash(CODES[raw], s, e), strict=True) if int(h) % 8 == 0} | {i + 1 for i, c in enumerate(raw) if c == 10} | {len(raw)}) if len(raw) else []
        return collections.Counter(raw[a:b].tobytes() for a, b in zip([0, *cuts], cuts, strict=False) if b > a)

    def like(a, b):
        x, y = leaves(a), leaves(b)
        return 1.0 if a == b else 2 * (x & y).total() / max(x.total() + y.total(), 1)

    texts = [t or "" for _, t in fixture()]
    got = {x["doc_id"]: x for x in merkle.edited_against_next(docs).collect()}
    for i, t in enumerate(texts):
        after = texts[(i + 1) % len(texts)]
        edit = t[: len(t) - len(t) // 2] + after[: len(t) // 2]
        assert got[i]["n_chars"] == len(t) and got[i]["edited_sha256"] == hashlib.sha256(edit.encode()).hexdigest()
        assert abs(got[i]["near_edited"] - like(t, edit)) < 1e-6 and abs(got[i]["near_next"] - like(t, after)) < 1e-6
        assert (got[i]["fingerprint"] == got[i]["edited_fingerprint"]) == (t == edit)


def test_repair(docs):
    shards = repair.write_shards(docs, HF)
    at, want = 0, {}
    for i, ids in ids_of(2).items():
        want[i] = (i, at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert {x["doc_id"]: tuple(x) for x in repair.read_documents(shards).collect()} == want


def test_grammar_random_access():
    r = np.random.default_rng(2)
    ids = np.concatenate([np.tile(r.integers(0, 50, 7), 40), r.integers(0, 50000, 300), np.tile([9, 9, 9, 9, 9], 30)]).astype(np.uint32)
    g = repair.compress(ids, least=3)
    assert len(g.sequence) < 0.6 * len(ids) and (g.decode() == ids).all()
    for a in range(0, len(ids), 37):
        assert (g.decode(a, 23) == ids[a : a + 23]).all()
    assert len(repair.compress(np.zeros(0, np.uint32)).decode()) == 0
    pairs = collections.Counter()
    i = 0
    while i < len(g.sequence) - 1:  # pairs that do not overlap, from the left
        pair = tuple(g.sequence[i : i + 2].tolist())
        pairs[pair] += 1
        i += 2 if pair[0] == pair[1] else 1
    assert max(pairs.values()) < 3, "no frequent pair is left"


def test_packing(docs):
    rows = packing.pack(docs, HF, window=256, shard_docs=6, shard_ids=3000).collect()
    want, by_doc, by_seq = ids_of(1), collections.defaultdict(list), collections.defaultdict(list)
    for x in rows:
        by_doc[x["doc_id"]].append(x)
        by_seq[x["sequence_id"]].append(x)
    assert set(by_doc) == set(want)
    for i, ids in want.items():
        at = 0
        for x in sorted(by_doc[i], key=lambda x: x["start"]):
            assert (x["start"], x["doc_tokens"], x["ids_crc32"]) == (at, len(ids), zlib.crc32(ids[at : at + x["length"]].tobytes()))
            at += x["length"]
        assert at == len(ids)
    for xs in by_seq.values():
        at = 0
        for x in sorted(xs, key=lambda x: x["offset"]):
            assert x["offset"] == at
            at += x["length"]
        assert at <= 256


def test_packing_prefers_neighbours():
    r = np.random.default_rng(0)
    docs = [np.concatenate([r.integers(0, 60, 40) + 1000 * (i % 3), [1]]).astype(np.uint16) for i in range(30)]
    df = np.bincount(np.concatenate([np.unique(d) for d in docs]), minlength=1 << 16)
    order = packing.arrange(docs, packing.Index(docs, df, 30, 41.0), 410)
    assert sorted(order) == list(range(30))
    same = np.mean([order[i] % 3 == order[i + 1] % 3 for i in range(29)])
    assert same > 0.6


PAGE = '<html><head><title>T</title><style>p{}</style><script>var x="</p>"</script></head><body><nav><ul><li><a href="/a">Home</a></li><li><a href="/b">News</a></li></ul></nav><div class="ad">Buy now cheap</div><article><h1>Title %d &amp; more</h1><p>First   paragraph\nof some length, number %d.</p><p><b>Second<br><p>Third paragraph with enough words to read.</p></article><footer>&copy; 2020 site</footer></body></html>'


def test_html(spark):
    rows = [(i, "u", PAGE % (i, i)) for i in range(60)] + [(60, None, None), (61, "u", ""), (62, "u", PAGE[: PAGE.index("enough")])]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {x["page_id"]: x["text"] for x in html_blocks.main_text(df, sample=40).collect()}
    for i in range(60):
        assert got[i] == f"Title {i} & more\nFirst paragraph of some length, number {i}.\nSecond\nThird paragraph with enough words to read."
    assert got[60] == got[61] == "" and got[62].endswith("Third paragraph with")


def test_html_without_telling_names():
    """Held-out pages without classes and ids, and with all parts as plain div: blocks of the article are found by position and words."""
    import re

    import duckdb

    pages = [x[0] for x in duckdb.sql("SELECT html FROM '/root/testdata/sf0.01/pages.parquet' ORDER BY page_id").fetchall()]
    weights = html_blocks.train(pages[:150])
    bare = lambda h: re.sub(r'\s(?:class|id|role)="[^"]*"', "", h)
    plain = lambda h: re.sub(r"</?(article|main|nav|footer|aside|header|section)\b[^>]*>", lambda m: "</div>" if m[0][1] == "/" else "<div>", bare(h))
    for change, precision in ((str, 0.99), (bare, 0.85), (plain, 0.75)):
        hit = found = wanted = 0
        for h, got in zip(pages[150:], html_blocks.extract([change(h) for h in pages[150:]], weights), strict=True):
            want, have = collections.Counter(t for p, t, _ in html_blocks.blocks(h) if html_blocks.told(p) == 1), collections.Counter(got.split("\n") if got else [])
            hit, found, wanted = hit + (want & have).total(), found + have.total(), wanted + want.total()
        assert hit / found >= precision and hit / wanted >= 0.99


def test_html_edge_cases(spark):
    """Unclosed quotes, self-closed elements, nulls, repeated rows, clashing columns, a very long page."""
    assert [t for _, t, _ in html_blocks.blocks('<div><p title="x>a b</p><p>c</p></div>')] == ["a b", "c"]
    assert [t for _, t, _ in html_blocks.blocks("<svg/><p>x</p>")] == ["x"]
    long = PAGE.replace("Second", "Second " * 60000) % (7, 7)
    rows = [(i, "u", PAGE % (i, i), "a", 1) for i in range(40)] + [(3, "u", PAGE % (3, 3), "a", 1), (None, None, None, None, None), (50, "v", long, "a", 1)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars long")
    got = html_blocks.main_text(df, sample=30).collect()
    assert len(got) == 43 and len({x["text"] for x in got if x["page_id"] == 3}) == 1
    assert next(x for x in got if x["page_id"] == 50)["n_chars"] > 400_000 and next(x for x in got if x["page_id"] is None)["text"] == ""


def test_html_gradient():
    """Backpropagation against differences."""
    net = html_blocks.Network()
    found = html_blocks.blocks(PAGE % (1, 1))
    batch, y = [html_blocks.Features(found), html_blocks.Features(found[:3])], [np.array([float(html_blocks.told(p) or 0) for p, _, _ in found]), np.zeros(3)]

    def loss():
        s = net.scores(batch)
        return sum(float((np.logaddexp(0, a) - b * a).sum()) for a, b in zip(s, y, strict=True)) / sum(map(len, y))

    grad = net.gradients(batch, y)
    for name in ("out", "wf", "wb", "cf", "cb"):
        at = np.unravel_index(np.argmax(abs(grad[name])), grad[name].shape)
        keep = net.p[name][at]
        net.p[name][at] = keep + 1e-5
        up = loss()
        net.p[name][at] = keep - 1e-5
        down = loss()
        net.p[name][at] = keep
        assert abs((up - down) / 2e-5 - grad[name][at]) < 1e-6


def test_empty_tables(spark):
    e = empty(spark)
    for df in (minhash.near_duplicates(e), bpe.encode_and_decode(e, TIK), merkle.edited_against_next(e), debruijn.without_repeated_words(e), repeats.without_repeated_bytes(e), repair.read_documents(repair.write_shards(e, HF)), packing.pack(e, HF), embed.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>")), html_blocks.main_text(spark.createDataFrame([], "page_id long, url string, html string"))):
        assert df.count() == 0


def test_repeated_and_null_ids(spark):
    t = words(random.Random(9), 80)
    df = spark.createDataFrame([(1, t), (1, t), (None, t), (5, t), (None, None)], "doc_id long, text string")
    assert sorted(x["n_removed"] for x in debruijn.without_repeated_words(df).collect()) == [0, 0, 80, 80, 80]
    assert len(bpe.encode_and_decode(df, TIK, long_chars=10, chunk_chars=50, overlap=5).collect()) == 5
    assert len(merkle.edited_against_next(df).collect()) == 5
    assert sum(x["n_tokens"] for x in repair.read_documents(repair.write_shards(df, HF)).collect()) > 5
    assert {x["doc_id"] for x in packing.pack(df, HF).collect()} == {None, 1, 5}


def test_pipeline(spark, sf_dir):
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = table(spark, sf_dir, "documents")
    kept = pipeline.drop_toxic(spark, docs, sf_dir)
    assert kept.columns == docs.columns and 0 < kept.count() <= docs.count()
    once = pipeline.drop_near_copies(spark, docs, sf_dir)
    sets = {x["doc_id"]: shingles(x["text"], 5) for x in docs.collect()}
    comp = reach(sets, [(a, b) for a in sets for b in sets if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])])
    assert sorted(x["doc_id"] for x in once.collect()) == sorted(i for i in sets if comp[i] == i)
    cut = pipeline.cut_repeated_spans(spark, docs, sf_dir)
    assert cut.columns == docs.columns and cut.count() == docs.count() and [f.dataType for f in cut.schema] == [f.dataType for f in docs.schema]
    assert [n for n, _ in pipeline.STAGES] == ["toxicity", "minhash", "suffix_array", "packing"]


def test_pipeline_end_to_end(spark, sf_dir):
    """run() against each stage by plain Python on what the one before it keeps."""
    import corpus_pipeline as pipeline

    docs = table(spark, sf_dir, "documents")
    kept = {x["doc_id"]: x["text"] for x in pipeline.drop_toxic(spark, docs, sf_dir).collect()}
    sets = {i: shingles(t, 5) for i, t in kept.items()}
    comp = reach(sets, [(a, b) for a in sets for b in sets if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])])
    kept = {i: (t or "").encode() for i, t in kept.items() if comp[i] == i}
    first, texts = {}, {}
    for i in sorted(kept):
        for a in range(len(kept[i]) - 49):
            first.setdefault(kept[i][a : a + 50], i)
    for i, t in kept.items():
        gone = bytearray(len(t))
        for a in range(len(t) - 49):
            if first[t[a : a + 50]] < i:
                gone[a : a + 50] = b"\1" * 50
        texts[i] = bytes(c for c, g in zip(t, gone, strict=True) if not g).decode("utf-8", "ignore")
    from tokenizers import Tokenizer

    tool, rows = Tokenizer.from_file(HF), collections.defaultdict(list)
    for x in pipeline.run(spark, sf_dir).collect():
        rows[x["doc_id"]].append(x)
    assert set(rows) == set(texts)
    for i, t in texts.items():
        ids = np.array([*tool.encode(t, add_special_tokens=False).ids, 1], "<u4")
        assert sum(x["length"] for x in rows[i]) == len(ids) == rows[i][0]["doc_tokens"]
        assert all(x["ids_crc32"] == zlib.crc32(ids[x["start"] : x["start"] + x["length"]].tobytes()) for x in rows[i])


def test_packing_places_like_texts_in_one_shard(spark):
    """Neighbours in a window share a topic far more often than by chance, of which an index shard of documents dealt by a hash would hold one or two texts."""
    r = random.Random(5)
    topics = [[f"w{t}x{r.randrange(10**6)}" for _ in range(20)] for t in range(50)]
    df = spark.createDataFrame([(i, " ".join(r.choice(topics[i % 50]) for _ in range(30))) for i in range(600)], "doc_id long, text string").repartition(3)
    rows = sorted(packing.pack(df, HF, window=1024, shard_docs=60).collect(), key=lambda x: (x["sequence_id"], x["offset"]))
    assert {x["doc_id"] for x in rows} == set(range(600))
    same = [a["doc_id"] % 50 == b["doc_id"] % 50 for a, b in zip(rows, rows[1:], strict=False) if a["sequence_id"] == b["sequence_id"] and a["doc_id"] != b["doc_id"]]
    assert np.mean(same) > 0.5, np.mean(same)


def test_packing_scores_are_bm25(monkeypatch):
    """Scores with a dense and a listed part of the vocabulary against the formula, over the corpus's frequencies; a query is all ids of its seed."""
    monkeypatch.setattr(packing, "DENSE", 20)
    r = np.random.default_rng(1)
    docs = [np.concatenate([r.integers(0, 200, r.integers(0, 80)), [1]]).astype(np.uint16) for _ in range(40)]
    df = np.bincount(np.concatenate([np.unique(d) for d in docs]), minlength=1 << 16) * 3
    index, counts = packing.Index(docs, df, 120, 41.0), [collections.Counter(d.tolist()) for d in docs]
    for a in range(40):
        want = [sum(np.log(1 + (120 - df[t] + 0.5) / (df[t] + 0.5)) * counts[b][t] * 2.2 / (counts[b][t] + 1.2 * (0.25 + 0.75 * len(docs[b]) / 41)) for t in counts[a] if t in counts[b]) for b in range(40)]
        assert np.allclose(index.scores(a), want, atol=1e-3) or np.allclose(np.delete(index.scores(a), a), np.delete(want, a), atol=1e-3)


def test_packing_pads_little_and_bounds_shards(spark, sf_dir):
    """On the table, padding is at most one window a range; documents longer than a shard and rows of one id are packed whole."""
    df = table(spark, sf_dir, "documents")
    rows = packing.pack(df, HF).collect()
    used, seqs = sum(x["length"] for x in rows), len({x["sequence_id"] for x in rows})
    assert seqs * 2048 - used < 2048 and len({x["doc_id"] for x in rows}) == df.count()
    two = spark.createDataFrame([(1, "same words " * 400), (1, "same words " * 400), (2, None), (None, "x"), (3, "long one " * 5000)], "doc_id long, text string")
    got = packing.pack(two, HF, window=128, shard_ids=1000).collect()
    assert sum(x["length"] for x in got if x["doc_id"] == 1) == 2 * max(x["doc_tokens"] for x in got if x["doc_id"] == 1)
    assert {x["doc_id"] for x in got} == {1, 2, 3, None}


def test_merkle_shows_and_compares_whole_trees():
    """Likeness counts every leaf of a long text, and the fingerprint names them all."""
    a = words(random.Random(3), 6000).replace(" alpha", "\nalpha")
    b = a[: len(a) // 2] + words(random.Random(8), 3000)
    leaves = [[x[0] for _, ps in merkle.tree(t)[1] for _, ls in ps for x in ls] for t in (a, b)]
    both = (collections.Counter(leaves[0]) & collections.Counter(leaves[1])).total()
    assert len(leaves[0]) > 600 and merkle.likeness(merkle.tree(a), merkle.tree(b)) == 2 * both / (len(leaves[0]) + len(leaves[1]))
    sections = [x.split(":")[1] for x in merkle.fingerprint(a).split(":", 1)[1].split("|")]
    assert [h for s in sections for p in s.split(";") for h in p.split("=")[1].split(".")] == [h[:4].hex() for h in leaves[0]]
    assert merkle.likeness(merkle.tree(a), merkle.tree(a)) == 1.0 and 1 > merkle.likeness(merkle.tree(a), merkle.tree("x" + a)) > 0.99


def test_html_keeps_text_of_unclosed_and_unusual_elements():
    page = '<body><header><a><svg class="i"/></a></header><article><p>first <math><mi>x</mi><mo>=</mo><mn>2</mn></math> end</p><p>a <svg><path d="M0"/></svg> b</p><button>open<p>second</p><noscript><p>third</p></noscript><object>fourth</object></article></body>'
    found = [t for _, t, _ in html_blocks.blocks(page)]
    assert found[:2] == ["first x=2 end", "a b"] and {"second", "third", "fourth"} <= set(found) and any("open" in t for t in found)
    assert html_blocks.blocks("<p>a</p><script>x<p>y</p>") == html_blocks.blocks("<p>a</p>")


def test_added_tokens_as_the_library_has_them():
    from tokenizers import Tokenizer

    t, e = Tokenizer.from_file(HF), tokens.Encoder("tokenizers", HF)
    mark = "<|endoftext|>"
    texts = [f"a {mark} b", mark, f"{mark}{mark}", "", f"x  {mark}  it's\n", "plain <text> <|endoftext|", f"é{mark}中", "<|endof" , "text|>", "end"]
    want = [t.encode(x, add_special_tokens=False).ids for x in texts]
    ids, n = e.encode(np.frombuffer("".join(texts).encode("utf-32-le"), np.uint32), np.cumsum([0, *map(len, texts)]))
    assert [x.tolist() for x in np.split(ids, np.cumsum(n)[:-1])] == want and 50256 in want[0]


def test_signature_bound_loses_no_more_than_the_bands():
    from math import ceil, comb

    least = ceil(minhash.AGREE * 128)
    assert sum(comb(128, i) * 0.8**i * 0.2 ** (128 - i) for i in range(least)) < 1e-8
