"""Each operator against brute force, exact round trips or held-out labels, and on awkward rows."""

import collections
import hashlib
import math
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest

from walkembed.llm import ann, ngram_join, packing, quality_nbsvm, quality_rules, secrets, sharding, toxicity, unigram, url_filter
from walkembed.llm.components import connected_components
from walkembed.llm.runtime import read_table
from walkembed.llm.wordcache import encoder

SF = "/root/testdata/sf0.001"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
AWKWARD = [(1, None), (2, ""), (3, " \n\t"), (4, "word"), (4, "word"), (None, "word two"), (6, "x" * 5000), (7, "é ü ☃ 😀 \x00 \x1c end"), (8, "a b c d e f g h i j " * 40)]


@pytest.fixture(scope="session")
def awkward(spark):
    """Rows with nulls, empty and long texts, repeats, and an extra column with a clashing name."""
    return spark.createDataFrame([(i, t, "s", 1) for i, t in AWKWARD], "doc_id long, text string, score string, n_words long")


@pytest.fixture(scope="session")
def docs(spark):
    return read_table(spark, SF, "documents")


@pytest.fixture(scope="session")
def labels(spark):
    return read_table(spark, SF, "labels")


def shingles(text, width=5):
    words = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))
    return frozenset(tuple(words[k : k + width]) for k in range(len(words) - width + 1)) if len(words) >= width else frozenset([tuple(words)] if words else [])


def brute_components(rows):
    sets = {i: shingles(t) for i, t in rows}
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            common = len(sets[a] & sets[b])
            if common and 100 * common >= 80 * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                up[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_join_equals_brute_force(spark, docs):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    rng = np.random.default_rng(0)
    base = [f"w{k}" for k in range(120)]
    for n in range(60):  # a drifting family: neighbours link, distant members don't
        words = list(base)
        for p in rng.choice(120, 2 + n % 9, replace=False):
            words[p] = f"x{rng.integers(1000)}"
        rows.append((10_000 + n, " ".join(words)))
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicates(frame).collect()}
    assert got == brute_components(rows)


def test_join_of_awkward_rows(spark, awkward):
    got = [(r["doc_id"], r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicates(awkward).collect()]
    assert len(got) == len(AWKWARD) and got.count((4, 1, 4)) == 2 and (1, 0, 1) in got and (None, 1, None) in got
    assert ngram_join.near_duplicates(awkward.where("false")).count() == 0


def test_group_links_match_all_pairs():
    rng = np.random.default_rng(2)
    sets = [np.unique(np.concatenate([rng.choice(200, 60, replace=False), rng.integers(1000, 9999, 4)])).astype(np.uint64) for _ in range(20)]
    sets += [np.unique(np.concatenate([s[: len(s) - k], np.arange(5000 + 10 * k, 5000 + 11 * k, dtype=np.uint64)])) for s in sets[:6] for k in (2, 5, 8)]
    n = np.array([len(s) for s in sets])
    need = [len(s) - ngram_join.need(len(s), 80) + 1 for s in sets]
    ids = np.arange(len(sets))
    links = set(ngram_join._group_links(ids, n, ids, np.zeros(len(sets), int), None, sets, need, [[s[:k] for s, k in zip(sets, need)]] * 2, 80))
    up = {i: i for i in ids.tolist()}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    want = dict(up)
    for a, b in links:
        up[find(max(a, b))] = find(min(a, b))
    got = [find(i) for i in ids.tolist()]
    up = want
    for a in ids.tolist():
        for b in range(a):
            common = len(np.intersect1d(sets[a], sets[b]))
            if ngram_join.linked(int(n[a]), int(n[b]), common, 80):
                up[find(a)] = find(b)
    same = lambda x: [[p == q for q in x] for p in x]
    assert same(got) == same([find(i) for i in ids.tolist()])


def test_components(spark):
    edges = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (8, 7), (5, 5), (20, 3)], "a long, b long")
    assert {r["vertex"]: r["component"] for r in connected_components(edges).collect()} == {1: 1, 2: 1, 3: 1, 20: 1, 7: 7, 8: 7, 9: 7}


def check_pack(rows, texts):
    words = encoder(packing.default_tokenizer())
    seqs, pieces = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
        pieces[r["doc_id"]].append(r)
    for spans in seqs.values():
        at = 0
        for offset, size in sorted(spans):
            assert offset == at and size > 0
            at += size
        assert at <= 2048
    for i, text in texts.items():
        ids = np.array(words.tokenizer.encode(text or "", add_special_tokens=False).ids + [1], dtype="<u4")
        at = 0
        for r in sorted(pieces[i], key=lambda r: r["start"]):
            assert r["start"] == at and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(ids[at : at + r["length"]].tobytes())
            at += r["length"]
        assert at == len(ids)
    used = [sum(s for _, s in spans) for spans in seqs.values()]
    return sum(packing.padding(u, 2048) for u in used) / sum(used)


def test_packing_covers_every_id(docs):
    rows = packing.pack(docs).collect()
    assert check_pack(rows, {r["doc_id"]: r["text"] for r in docs.collect()}) < 0.02


def test_packing_of_awkward_rows(spark, awkward):
    unique = awkward.where("doc_id is not null").dropDuplicates(["doc_id"]).coalesce(1)
    check_pack(packing.pack(unique).collect(), {i: t for i, t in AWKWARD if i is not None})
    assert packing.pack(awkward).where("start = 0").count() == len(AWKWARD)
    assert packing.pack(awkward.where("false")).count() == 0


def test_cuts_are_optimal():
    rng = np.random.default_rng(1)
    for _ in range(20):
        at = np.unique(np.append(rng.integers(1, 200, 30), 200))
        at = np.unique(np.concatenate([at, np.arange(16, 200, 16)]))
        penalty = rng.integers(0, 20, len(at))
        cuts = packing.best_cuts(at, penalty, 32)
        pen = dict(zip(at.tolist(), penalty.tolist()))
        best = {0: 0}
        for p in at.tolist():
            best[p] = min(c + 32 - (p - q) + pen[p] + packing.WINDOW for q, c in best.items() if p - q <= 32)
        cost = sum(32 - (b - a) + pen[b] + packing.WINDOW for a, b in zip([0, *cuts], cuts))
        assert cuts[-1] == 200 and cost == best[200]


@pytest.mark.parametrize("length", [20, 32, 64, 100, 256])
def test_cuts_are_optimal_with_powers_of_two(length):
    rng = np.random.default_rng(2)
    for _ in range(20):
        at = np.unique(np.concatenate([rng.integers(1, 600, 60), np.arange(16, 600, 16), [600]]))
        penalty = rng.integers(0, 25, len(at))
        cuts = packing.best_cuts(at, penalty, length)
        pen = dict(zip(at.tolist(), penalty.tolist()))
        pad = lambda size: packing.padding(size, length) if size >= 32 else length - size
        best = {0: 0}
        for p in at.tolist():
            best[p] = min(c + pad(p - q) + pen[p] + packing.WINDOW for q, c in best.items() if p - q <= length)
        assert cuts[-1] == 600 and max(np.diff([0, *cuts])) <= length
        assert sum(pad(b - a) + pen[b] + packing.WINDOW for a, b in zip([0, *cuts], cuts)) == best[600]


def test_long_sentences_offer_cuts():
    at, _ = packing.cut_candidates(1000, np.array([1000]), np.array([400]), 2048)
    assert max(np.diff([0, *at])) <= 32


def test_quality_on_held_out(spark, docs, labels):
    rows = quality_nbsvm.classify(docs, labels).join(labels, "doc_id").where("held_out").collect()
    assert all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.7) for r in rows)
    assert np.mean([r["predicted"] == r["quality"] for r in rows]) >= 0.8
    assert all((zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) == r["held_out"] for r in rows)


def test_classifiers_on_awkward_rows(spark, awkward, labels):
    for op in (quality_nbsvm.classify, toxicity.classify):
        rows = op(awkward, labels).collect()
        assert len(rows) == len(AWKWARD) and all(0 <= r["score"] <= 1 for r in rows)
        assert op(awkward.where("false"), labels).count() == 0
        assert len(op(awkward, labels.where("false")).collect()) == len(AWKWARD)


def score(text, lexicon=toxicity.Lexicon()):
    [(_, _, raw, offsets)] = list(quality_nbsvm.text_slices(pa.array([text])))
    return 1 - math.exp(-lexicon.scale * toxicity.text_sums(quality_nbsvm.find_words(raw, offsets), toxicity.Automaton(lexicon), lexicon.spared)[0])


def test_toxicity_context_and_spelling():
    assert score("You are an idiot.") >= 0.7 and score("YOU M0RON, you stupld fool") >= 0.7
    assert score('They called it "idiot" in the report.') < 0.7 and score("a calm day by the sea") == 0


def test_toxicity_of_a_lone_misspelling():
    assert score("My neighbour is a complete morron.") >= 0.7 and score("What a ztupid plan.") >= 0.7
    assert score("The crash of the crown, a closer regard for the laser, apathetic and discussing a lower reward.") == 0
    assert score('They called him a "morron" in the report.') < 0.7
    plain = ["a day by the sea %d" % k for k in range(8)]
    lexicon = toxicity.fit(["what an idiot he is"] * 8 + plain, [1] * 8 + [0] * 8)
    assert score("he is a complete morron", lexicon) >= 0.7
    # spared are words near a term in clean rows, also by the first letter, and they do not hide a text from the stems
    texts = ["the tidiot gronkle went %s" % w for w in ("home", "out", "there", "by")]
    lexicon = toxicity.fit(texts + plain + ["a tidiot bird"] * 4, [1] * 4 + [0] * 12)
    assert any("gronkle".startswith(t) for t in lexicon.stems) and score("a tidiot bird", lexicon) == 0 and score("gronkle", lexicon) >= 0.7
    # labels move the scale up as well as down
    quoted = ['they called him "idiot" again'] * 8
    assert toxicity.fit(quoted + plain, [1] * 8 + [0] * 8).scale > toxicity.SCALE and score(quoted[0], toxicity.fit(quoted + plain, [1] * 8 + [0] * 8)) >= 0.7
    assert toxicity.fit(["you idiot and moron", *plain, "a clown"], [1] + [0] * 9).scale < toxicity.SCALE


def edit_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row, last = [i], row
        for j, y in enumerate(b, 1):
            row.append(min(last[j] + 1, row[-1] + 1, last[j - 1] + (x != y)))
    return row[-1]


def test_automaton_equals_edit_distance():
    terms = ["moron", "pathetic", "worthless", "scum"]
    automaton = toxicity.Automaton(toxicity.Lexicon({t: 1.0 for t in terms}))
    rng = np.random.default_rng(4)
    for _ in range(2000):
        word = list(terms[rng.integers(4)])
        for _ in range(rng.integers(0, 4)):
            k = rng.integers(1, len(word) + 1)
            word[k : k + rng.integers(0, 2)] = list(rng.choice(list("abcxyz"), rng.integers(0, 2)))
        word = "".join(word)
        raw = np.frombuffer(word.encode(), dtype=np.uint8)
        found = len(automaton.match(raw, np.array([0]), np.array([len(raw)]))[0]) > 0
        near = any(word[0] == t[0] and edit_distance(word[1:], t[1:]) <= toxicity.edits_allowed(t) for t in terms)
        assert found == near, word


def brute_counts(text):
    w = WORD.findall(text or "")
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    grams = collections.Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    cover = {j for i in range(len(w) - 7) if grams[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    return [len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(cover)]


def test_rules_equal_brute_force(docs, labels, awkward):
    for frame in (docs, awkward):
        texts = [(r["doc_id"], r["text"]) for r in frame.collect()]
        rows = quality_rules.screen(frame, labels).collect()
        got = collections.Counter((r["doc_id"], *(r[c] for c in quality_rules.COUNTS), r["base_failed"]) for r in rows)
        want = collections.Counter()
        for i, t in texts:
            c = brute_counts(t)
            want[(i, *c, c[0] < 20 or 100 * c[4] > 30 * c[0])] += 1
        assert got == want and not any(r["kept"] and r["base_failed"] for r in rows)


def test_forest_isolates_outliers():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 3))
    forest = quality_rules.grow(np.vstack([x, [[9, 9, 9]]]))
    assert forest.score(np.array([[9.0, 9, 9]]))[0] > np.quantile(forest.score(x), 0.99)


def test_forest_and_cut_use_every_labelled_row(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(6000, 8)).round(3)
    y = np.arange(6000) % 2
    frame = spark.createDataFrame([(int(k), *map(float, row)) for k, row in zip(y, x)], "label int, " + ", ".join(f"{c} double" for c in quality_rules.SHAPES)).repartition(5)
    forest = quality_rules.fit(frame)
    want = quality_rules.grow(x)
    assert forest.sample == 6000 and np.array_equal(forest.cut, want.cut) and np.array_equal(forest.depth, want.depth)
    scores = want.score(x)
    low = np.sort(scores[y == 1])[2993]
    higher = scores[(y == 0) & (scores > low)]
    assert forest.threshold == pytest.approx((low + np.quantile(higher, 0.25)) / 2 if len(higher) else low + 0.05, abs=1e-12)
    rows = spark.createDataFrame([(float(v),) for v in scores], "s double")
    assert [quality_rules.ranked(rows, k, 100) for k in (0, 777, 5999)] == np.sort(scores)[[0, 777, 5999]].tolist()


def test_secrets_equal_plain_patterns(docs, awkward):
    for frame in (docs, awkward):
        texts = {r["doc_id"]: r["text"] or "" for r in frame.collect()}
        for r in secrets.scan(frame).collect():
            t = texts[r["doc_id"]] if frame is docs or r["doc_id"] in (1, 2, 6, 7, 8) else None
            if t is None:
                continue
            s = [(*k.span(), "assign") for k in re.finditer(r"(?ai)(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", t) if len(k[2]) >= 12]
            s += [(*k.span(), "access") for k in re.finditer(r"AKIA[A-Z0-9]+", t) if len(k[0]) >= 18]
            s += [(*k.span(), "hex") for k in re.finditer(r"[0-9a-f]+", t) if len(k[0]) >= 16]
            s.sort(key=lambda q: (q[0], secrets.KINDS.index(q[2])))
            assert r["base_sha256"] == hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, b, k in s).encode()).hexdigest()
            assert [r[f"n_{k}"] for k in ("assign", "access", "hex")] == [sum(x[2] == k for x in s) for k in ("assign", "access", "hex")]


def test_markov_ratio_on_fresh_samples():
    model = secrets.MarkovRatio()
    fresh = secrets.labelled_samples(99)
    assert np.mean([(model(t) > model.cut) == bool(k) for t, k in fresh]) > 0.95
    assert secrets.blanked("a token = 'abcdefghijkl1234' b", secrets.find_spans("a token = 'abcdefghijkl1234' b", model)[1]).count("[SECRET]") == 1


def test_urls(spark):
    cases = [
        (1, "http://A.net/x?y", "a.net", "/x", "net/", "block"), (2, "https://www.example.net/en/1#f", "www.example.net", "/en/1", "example.net/en/", "allow"),
        (3, "http://example.com/de/1", "example.com", "/de/1", "example.com/de/", "block"), (4, "http://b.org/fr/", "b.org", "/fr/", "org/fr/", "allow"),
        (5, "http://free-bets.example.com/en/2", "free-bets.example.com", "/en/2", None, "block"), (6, "http://library.example.com/en/2", "library.example.com", "/en/2", None, "allow"),
        (7, None, "", "", None, "allow"), (8, "no scheme", "", "", None, "allow"), (9, "http://a.net", "a.net", "", None, None), (10, "x://É.NET?a=/", "É.net", "", None, None),
    ]
    rows = {r["page_id"]: r for r in url_filter.judge(spark.createDataFrame([(c[0], c[1], "h") for c in cases], "page_id long, url string, host string")).collect()}
    for i, _, host, path, rule, verdict in cases:
        assert (rows[i]["host"], rows[i]["path"], rows[i]["rule"]) == (host, path, rule)
        assert verdict is None or rows[i]["verdict"] == verdict
    assert url_filter.judge(read_table(spark, SF, "pages").where("false")).count() == 0


def test_lookup_table_by_turns():
    shards, slots = ["b", "a", "c"], 13
    order = {s: [(sharding._number(s, "offset") + k * (sharding._number(s, "skip") % (slots - 1) + 1)) % slots for k in range(slots)] for s in shards}
    want = [-1] * slots
    while -1 in want:
        for s in sorted(shards):
            if -1 in want:
                want[next(p for p in order[s] if want[p] < 0)] = shards.index(s)
    assert sharding.lookup_table(shards, slots) == want
    full, less = sharding.lookup_table(), sharding.lookup_table(sharding.SHARDS[:-1])
    counts = np.bincount(full)
    assert counts.max() - counts.min() <= 1 and np.mean([a != b for a, b in zip(full, less)]) < 0.1
    with pytest.raises(ValueError):
        sharding.lookup_table(shards, 12)


def test_sharding_of_awkward_rows(spark, awkward):
    rows = sharding.place(awkward.withColumnRenamed("score", "slot"), "doc_id").collect()
    assert len(rows) == len(AWKWARD) and len({r["shard"] for r in rows if r["doc_id"] == 4}) == 1
    assert not [x for x in ("Python", "Arrow", "Pandas") if x in sharding.place(awkward, "doc_id")._jdf.queryExecution().executedPlan().toString()]


def test_neighbours_recall_and_ties(spark):
    from pyspark.sql import functions as F

    frame = read_table(spark, SF, "embeddings").select("vec_id", "embedding")
    odd = spark.createDataFrame([(9001, None), (9002, [0.0] * 64), (9003, [float("nan")] * 64), (9004, [None] * 64), (9005, [1.0] * 3), (None, [1.0] * 64)], "vec_id long, embedding array<float>")
    seventh = frame.where("vec_id = 7").first()["embedding"]
    copies = spark.createDataFrame([(k, seventh) for k in range(20_001, 20_061)], "vec_id long, embedding array<float>")
    every = frame.unionByName(copies)
    ids, x = zip(*[(r["vec_id"], r["embedding"]) for r in every.collect()])
    ids, x = np.array(ids), np.array(x, dtype=float)
    found = collections.defaultdict(list)
    for r in ann.search(every.unionByName(odd), F.col("vec_id") % 100 == 0).orderBy("query_id", "rank").collect():
        found[r["query_id"]].append((r["vec_id"], r["score"]))
    hits = 0
    for q in ids[ids % 100 == 0].tolist():
        d = np.sqrt(((x - x[ids == q][0]) ** 2).sum(1))
        d[ids == q] = np.inf
        hits += len({v for v, _ in found[q]} & set(ids[np.lexsort((ids, d))[:10]].tolist()))
        assert len(found[q]) == 10 and all(abs(s - d[ids == v][0]) < 1e-9 for v, s in found[q])
    assert hits >= 0.9 * 10 * (ids % 100 == 0).sum()
    assert ann.search(every.where("false"), F.col("vec_id") % 100 == 0).count() == 0
    assert ann.search(every.where("vec_id in (0, 1)"), F.col("vec_id") % 100 == 0).count() == 1


def test_neighbours_among_near_copies():
    rng = np.random.default_rng(5)
    n, k = 6000, 10
    x = rng.normal(size=(n, 64))
    x[::3] = x[0] + 0.01 * rng.normal(size=(n // 3, 64))
    ids = rng.permutation(n)
    asked = np.r_[0:90:3, 1:60:3]
    query, vec, score = ann._block_search(ids[asked], x[asked], ids, x, ann.Quantiser(x[:1024]), k, ann.RERANK)
    for i in asked.tolist():
        d = np.sqrt(((x - x[i]) ** 2).sum(1))
        near = np.lexsort((ids, d))
        near = near[near != i][:k]
        assert vec[query == ids[i]].tolist() == ids[near].tolist()
        assert np.allclose(score[query == ids[i]], d[near], rtol=0, atol=1e-12)


def test_unigram_is_optimal_and_lossless(awkward, docs):
    vocabulary = unigram.load_vocabulary(unigram.default_model())
    trie = unigram.DoubleArrayTrie(vocabulary)
    encoder_, decoder = unigram.UnigramEncoder(vocabulary, trie), unigram.Decoder(vocabulary)
    scores = {p: s for p, s, u in zip(vocabulary.pieces, vocabulary.scores, vocabulary.usable) if u}
    bytes_ = set(vocabulary.byte_id)

    def best(seg):
        out = [0.0] + [-math.inf] * len(seg)
        for i in range(len(seg)):
            for j in range(i + 1, len(seg) + 1):
                if seg[i:j] in scores:
                    out[j] = max(out[j], out[i] + scores[seg[i:j]])
            if seg[i] not in scores:
                out[i + 1] = max(out[i + 1], out[i] + encoder_.byte_score * len(seg[i].encode()))
        return out[-1]

    segments = ["▁hello", "world☃x", "▁", "▁internationalisation", "😀", "▁▁▁abc", "z" * 250]
    for seg, ids in zip(segments, encoder_.solve(segments)):
        value = sum(encoder_.byte_score if i in bytes_ else vocabulary.scores[i] for i in np.frombuffer(ids, "<u4"))
        assert abs(value - best(seg)) < 1e-6, seg
    for text in ["", " ", "  a  b ", "héllo\n\n wörld\t☃ 😀 end ", "▁ odd ▁", *(t for _, t in AWKWARD if t)]:
        assert decoder.decode(np.frombuffer(encoder_.encode([text])[0], "<u4")) == text
    for frame in (awkward, docs):
        rows = unigram.encode_documents(frame, emit_ids=True)
        assert rows.where("not round_trip").count() == 0 and rows.count() == frame.count()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert all(texts[r["doc_id"]] == r["text"] for r in unigram.decode_documents(unigram.encode_documents(docs, emit_ids=True)).collect())


def test_pipeline_equals_its_operators(spark):
    import corpus_pipeline as cp

    docs = read_table(spark, SF, "documents")
    labels = read_table(spark, SF, "labels")
    good = {r["doc_id"] for r in quality_nbsvm.classify(docs, labels).where("predicted = 1").collect()}
    calm = {r["doc_id"] for r in toxicity.classify(docs, labels).where("predicted = 0").collect()}
    left = [(r["doc_id"], r["text"]) for r in docs.collect() if r["doc_id"] in good & calm]
    heads = {i for i, (_, c) in brute_components(left).items() if i == c}
    model = secrets.MarkovRatio()
    want = {i: secrets.blanked(t, secrets.find_spans(t, model)[1]) for i, t in left if i in heads}
    rows = cp.run(spark, SF).collect()
    assert {r["doc_id"] for r in rows} == set(want)
    check_pack(rows, want)


def test_word_ids_equal_the_tokenizer():
    """Random strings of awkward characters, contractions, folds that grow, special tokens and joined plain words."""
    words = encoder(packing.default_tokenizer())
    rng = np.random.default_rng(9)
    alphabet = [*"abstdeSTİIßéÉÜǅ'\".,!?-_(<|>) \t\n\x0b\x1c\x1f\x85\xa0 ̇́Σσς字ﬁ12٣", "'s", "'ll ", "<|endoftext|>", "İ.", " 'tis ", "Word,", "'d. "]
    texts = ["", "'tis", "'S.", "''t", "('s)", "İ.", "(İ)", "aİ,", "x<|endoftext|>y", "'twas, don't \"'em\"", "Plain Words, here."]
    texts += ["".join(rng.choice(alphabet, rng.integers(1, 30))) for _ in range(4000)]
    ids, sizes = words.encode(pa.array([*texts, None], pa.large_string()))
    assert sizes[-1] == 0
    stop = np.cumsum(sizes)
    for text, lo, hi in zip(texts, stop - sizes, stop):
        assert ids[lo:hi].tolist() == words.tokenizer.encode(text, add_special_tokens=False).ids, repr(text)
    again, _ = words.encode(pa.array(texts, pa.string()))
    assert np.array_equal(ids, again)


def test_long_texts_are_encoded_in_pieces(monkeypatch):
    words = encoder(packing.default_tokenizer())
    texts = pa.array(["a b", "word, " * 400 + "x" * 300 + " end", None, "tail", "y" * 500], pa.string())
    whole = words.encode(texts)
    monkeypatch.setattr(packing, "_BLOCK_CHARS", 50)
    parts = list(packing._encoded(words, texts, [len(t or "") for t in texts.to_pylist()]))
    assert [lo for lo, *_ in parts][1:] == [hi for _, hi, *_ in parts][:-1] and parts[-1][1] == 5
    assert np.array_equal(np.concatenate([p[2] for p in parts]), whole[0]) and np.array_equal(np.concatenate([p[3] for p in parts]), whole[1])


def test_cuts_at_the_contract_length_try_every_power_of_two():
    rng = np.random.default_rng(5)
    for _ in range(6):
        at, penalty = packing.cut_candidates(9000, np.unique(np.append(rng.integers(1, 9000, 40), 9000)), rng.integers(1, 9000, 500), 2048)
        cuts = packing.best_cuts(at, penalty, 2048, 1)
        pen = dict(zip(at.tolist(), penalty.tolist()))
        best = {0: 0}
        for p in at.tolist():
            best[p] = min(c + packing.padding(p - q, 2048) + pen[p] + packing.WINDOW for q, c in best.items() if p - q <= 2048)
        assert sum(packing.padding(b - a, 2048) + pen[b] + packing.WINDOW for a, b in zip([0, *cuts], cuts)) == best[9000]


def test_neighbours_of_repeated_ids(spark):
    from pyspark.sql import functions as F

    frame = read_table(spark, SF, "embeddings").select("vec_id", "embedding").where("vec_id < 120")
    moved = frame.where("vec_id in (100, 5)").withColumn("embedding", F.transform("embedding", lambda v: v + F.lit(0.25).cast("float")))
    every = frame.unionByName(frame.where("vec_id in (0, 3)")).unionByName(moved).unionByName(frame.where("vec_id = 7").crossJoin(spark.range(30)).select("vec_id", "embedding"))
    rows = [(r["vec_id"], np.array(r["embedding"], dtype=float)) for r in every.collect()]
    want = []
    for q in (0, 100):
        best: dict = {}
        for name, x in rows:
            for _, asked in [r for r in rows if r[0] == q and name != q]:
                best[name] = min(best.get(name, np.inf), float(np.sqrt(((x - asked) ** 2).sum())))
        want += [(q, k, v) for k, (v, _) in enumerate(sorted(best.items(), key=lambda p: (p[1], p[0]))[:10], 1)]
    got = [(r["query_id"], r["rank"], r["vec_id"]) for r in ann.search(every, F.col("vec_id") % 100 == 0).orderBy("query_id", "rank").collect()]
    assert got == want


def test_toxicity_of_letters_with_marks():
    assert score("What an \u00efdi\u00f6t.") >= 0.7 and score("a real mo\u0308ron") >= 0.7 and score("such a l\u00f8s\u00e9r") >= 0.7
    assert score("caf\u00e9 na\u00efve \u00fcber 字字字字字") == 0
    text = "you idiot " * 200  # no limit of hits
    [(_, _, raw, offsets)] = list(quality_nbsvm.text_slices(pa.array([text])))
    lexicon = toxicity.Lexicon()
    assert toxicity.text_sums(quality_nbsvm.find_words(raw, offsets), toxicity.Automaton(lexicon), lexicon.spared)[0] > 200


def test_toxicity_on_held_out(docs, labels):
    rows = toxicity.classify(docs, labels).join(labels, "doc_id").where("held_out").collect()
    assert all(r["predicted"] == (r["score"] >= 0.7) and (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) == r["held_out"] for r in rows)
    assert np.mean([r["predicted"] == r["toxic"] for r in rows]) >= 0.9


def test_markov_spans_of_parts_and_letters():
    model = secrets.MarkovRatio()
    spans = lambda t: secrets.find_spans(t, model)[1]
    assert spans("see qwhzkvjxmpbtrlcnqwhzkv now") == [(4, 26, "model")]
    assert spans("usr/local/share/docs/x8Fk2PqLm9Zr7TnVb3Wc") == [(21, 41, "model")]
    for plain in ("-" * 40, "=" * 30, "_" * 25, "Donaudampfschifffahrtsgesellschaft", "internationalization_of_everything", "https/www/example/com/articles/2020/10/11"):
        assert spans(plain) == []


def test_samples_of_repeated_ids_are_the_same_on_every_run(spark):
    from walkembed.llm.runtime import labelled_sample

    docs = spark.createDataFrame([(1, "b"), (1, "a"), (2, "c"), (3, None), (None, "d")] * 3, "doc_id long, text string")
    marks = spark.createDataFrame([(1, 1), (2, 0), (2, 1), (3, 1), (None, 1), (9, None)], "doc_id long, quality int")
    assert labelled_sample(docs.repartition(7), marks, "quality", 10) == (["a", "c"], [1, 0])


def test_distinct_documents(spark):
    base = [f"w{k}" for k in range(60)]
    near = " ".join([*base[:59], "other"])
    rows = [(5, " ".join(base), 1), (5, near, 2), (5, "quite another text that links with nothing at all", 3), (3, " ".join(base), 4), (3, " ".join(base), 4), (None, "a b", 5), (None, "a b", 5), (8, None, 6), (8, "", 7), (9, None, 6), (7, near.upper(), 8)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, near_duplicate_text int")
    kept = sorted((r["doc_id"] or -1, r["text"] or "", r["near_duplicate_text"]) for r in ngram_join.distinct_documents(frame).collect())
    assert kept == sorted([(3, " ".join(base), 4), (5, rows[2][1], 3), (-1, "a b", 5), (-1, "a b", 5), (8, "", 6), (8, "", 7), (9, "", 6)])
    assert ngram_join.distinct_documents(frame.where("false")).count() == 0


def test_pipeline_stages_on_awkward_rows(spark, awkward):
    """Every stage takes nulls, empty and long texts, repeats, clashing columns and empty tables, and keeps the columns."""
    import corpus_pipeline as cp

    docs = awkward.withColumnRenamed("score", "ids").withColumnRenamed("n_words", "sequence_id")
    for table in (docs, docs.where("false")):
        for name, stage in cp.STAGES:
            out = stage(spark, table, SF)
            if name != "packing":
                assert out.columns == table.columns
            rows = out.collect()
            if name == "n-gram Jaccard join":
                assert len(rows) == max(0, table.count() - 1)  # one row repeats an id and its text
            if name == "secret scans":
                assert len(rows) == table.count()
            if name == "packing":
                assert len({r["doc_id"] for r in rows}) == len({r["doc_id"] for r in table.collect()})


def test_pieces_meet_in_salted_groups_and_large_cells(spark, monkeypatch):
    """A family whose members mostly don't link to its pivots, with groups and cells cut small and many edge parts."""
    from walkembed.llm import components

    rng = np.random.default_rng(11)
    rows = []
    for family in range(2):
        base = [f"f{family}w{k}" for k in range(90)]
        for n in range(70):
            words = list(base)
            for p in rng.choice(90, 1 + n % 5, replace=False):
                words[p] = f"x{rng.integers(10_000)}"
            rows.append((1000 * family + n, " ".join(words)))
    for name, value in (("_GROUP_PART", 10), ("_CELL_ROWS", 8), ("TOKENS_PER_RANGE", 500), ("_TOKENS_PER_BLOCK", 700), ("_TOKENS_PER_SET_BLOCK", 600), ("_PIVOTS", 1)):
        monkeypatch.setattr(ngram_join, name, value)
    monkeypatch.setattr(components.connected_components, "__defaults__", (60, 20))
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in ngram_join.near_duplicates(frame).collect()}
    assert got == brute_components(rows)


def test_link_counts_equal_brute_force(spark, monkeypatch):
    rng = np.random.default_rng(21)
    base = [f"w{k}" for k in range(80)]
    rows = []
    for n in range(50):
        words = list(base)
        for p in rng.choice(80, 1 + n % 4, replace=False):
            words[p] = f"x{rng.integers(1000)}"
        rows += [(n, " ".join(words))] * (1 + (n % 10 == 0))
    rows += [(100, "alone in the world of texts"), (101, None), (None, " ".join(base)), (102, "a b"), (103, "A  b")]
    sets = [shingles(t) if i is not None else frozenset() for i, t in rows]
    want = sorted((i if i is not None else -1, sum(1 for j, y in enumerate(sets) if j != k and x and y and 100 * len(x & y) >= 80 * len(x | y))) for k, ((i, _), x) in enumerate(zip(rows, sets)))
    for part in (None, 6):
        if part:
            monkeypatch.setattr(ngram_join, "_CELL_ROWS", part)
        got = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_links"]) for r in ngram_join.link_counts(spark.createDataFrame(rows, "doc_id long, text string")).collect())
        assert got == want
