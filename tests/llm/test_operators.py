"""Corpus operators against brute force, and on awkward tables."""

import collections
import random
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from cellgraph.llm import ann, htmltext, langid, linededup, mixing, packing, resemblance, simhash, tokencount, topk, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
AWKWARD = [
    (1, None, None, None, None), (2, "", "en", "a", 0), (3, "x" * 200_000, "en", "a", 200_000), (4, "same line\nother " * 3, "en", "b", 9),
    (5, "same line\nother " * 3, "en", "b", 9), (5, "same line\nother " * 3, "en", "b", 9), (6, "Ünï <|endoftext|> ՘ \U0001f600 ok", None, "b", 5), (None, "no id here", "en", "a", 3),
]


@pytest.fixture(scope="module")
def awkward(spark):
    return spark.createDataFrame(AWKWARD, DOCS).withColumn("size", F.lit(1)).withColumn("score", F.lit("x"))


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def _bpe():
    return tokencount.read_tokenizer()


def test_token_counts(spark, awkward, empty):
    library = Tokenizer.from_str(_bpe())
    want = collections.Counter((i, len(library.encode(t or "", add_special_tokens=False).ids)) for i, t, *_ in AWKWARD)
    assert collections.Counter((r["doc_id"], r["n_tokens"]) for r in tokencount.token_counts(awkward, _bpe()).collect()) == want
    assert tokencount.token_counts(empty, _bpe()).count() == 0


def test_merge_table_against_library():
    library, counter = Tokenizer.from_str(_bpe()), tokencount.TokenCounter(_bpe())
    rng = random.Random(1)
    for _ in range(300):
        text = "".join(rng.choice("abcdeé ñß12 .,\n\t'sA中ֈ") for _ in range(rng.randrange(60)))
        assert counter.count(text) == len(library.encode(text, add_special_tokens=False).ids), text


def test_packing_round_trip(spark, awkward, empty):
    library = Tokenizer.from_str(_bpe())
    ids = {(i, n): library.encode(t or "", add_special_tokens=False).ids + [0] for n, (i, t, *_) in enumerate(AWKWARD)}
    rows = packing.pack_documents(awkward, _bpe()).collect()
    assert sum(r["length"] for r in rows) == sum(map(len, ids.values()))
    of = {i: x for (i, _), x in ids.items()}
    for r in rows:
        piece = of[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(piece) == r["length"] and zlib.crc32(np.array(piece, dtype="<u4").tobytes()) == r["ids_crc32"]
    by = collections.defaultdict(list)
    for r in rows:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for pieces in by.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 1024
    assert packing.pack_documents(empty, _bpe()).count() == 0


def test_mixing(spark, awkward, empty):
    rows = [(i, f"s{i % 3}" if i % 7 else None, i % 11) for i in range(400)]
    got = mixing.mix(spark.createDataFrame(rows, "doc_id long, source string, size long")).collect()
    taken, target, size = collections.Counter(), {}, collections.Counter()
    for r in got:
        taken[r["source"]] += r["taken"]
        size[r["source"]] += r["size"]
        target[r["source"]] = r["target"]
        assert 0 <= r["taken"] <= 3 * r["size"]
    assert all(abs(taken[s] - target[s]) <= 1 and target[s] <= 3 * size[s] for s in target) and len(target) == 4
    assert abs(sum(target.values()) - sum(size.values())) < 1e-6
    assert mixing.mix_documents(awkward).count() == len(AWKWARD) and mixing.mix_documents(empty).count() == 0


def test_plan_targets_caps():
    assert mixing.plan_targets([("a", 10), ("b", 1000), (None, 90)], (5, 2, 1), 3) == pytest.approx({"a": 30.0, "b": 1070 * 2 / 3, None: 1070 / 3} if 1070 / 3 <= 270 else {"a": 30.0, "b": 800.0, None: 270.0})


def test_topk(spark):
    rng = np.random.default_rng(1)
    vecs = [(i, [float(x) for x in rng.integers(-3, 4, 6)]) for i in range(90)] + [(200, None), (201, [float("nan")] * 6), (202, []), (203, [1.0, None, 0.0, 0.0, 0.0, 0.0])]
    df = spark.createDataFrame(vecs, "id long, vec array<double>")
    got = [tuple(r) for r in topk.top_k(df, F.col("id") % 10 == 0, k=7, bins=4, block=16, query_block=3).orderBy("query_id", "rank").collect()]
    want = []
    for q, v in vecs[:90]:
        if q % 10 == 0:
            best = sorted((-int(np.dot(v, w)), c) for c, w in vecs[:90] if c != q)[:7]
            want += [(q, n + 1, c, -s) for n, (s, c) in enumerate(best)]
    assert got == want
    assert topk.top_k(df.where("false"), F.lit(True)).count() == 0


def test_ann_recall(spark):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((600, 16))
    rows = [(i, x[i].tolist()) for i in range(600)] + [(700, None), (701, [0.0] * 16), (702, x[0].tolist())]
    got = collections.defaultdict(dict)
    for r in ann.nearest(spark.createDataFrame(rows, "id long, vec array<double>"), F.col("id") % 50 == 0).collect():
        got[r["query_id"]][r["id"]] = r["score"]
    full = np.vstack([x, x[:1]])
    ids = [*range(600), 702]
    unit = full / np.linalg.norm(full, axis=1)[:, None]
    hits = total = 0
    for q in got:
        s = unit @ unit[ids.index(q)]
        best = [ids[j] for j in np.argsort(-s, kind="stable") if ids[j] != q][:5]
        hits += sum(b in got[q] for b in best)
        total += 5
        assert all(abs(score - s[ids.index(i)]) < 1e-12 for i, score in got[q].items())
    assert hits / total >= 0.9 and 700 not in got and 701 not in got


def _fingerprint(text):
    words = text.encode().lower().split()
    parts = [b" ".join(words[i : i + 3]) for i in range(len(words) - 2)] if len(words) >= 3 else ([b" ".join(words)] if words else [])
    hashes = [xxhash.xxh64_intdigest(p, 42) for p in parts]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


@pytest.mark.parametrize("hot", [64, 1])
def test_simhash_links(spark, hot):
    rng = random.Random(4)
    fps = [rng.getrandbits(64) for _ in range(20)]
    for _ in range(150):
        fps.append(rng.choice(fps) ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64) if rng.random() < 0.5 else 0))
    fps = sorted(set(fps))
    signed = [(f - (1 << 64) if f >> 63 else f, i) for i, f in enumerate(fps)]
    from cellgraph.algorithms.contraction import components
    from cellgraph.scratch import Scratch

    scratch = Scratch(spark, "test")
    edges = simhash.linked_fingerprints(spark.createDataFrame(signed, "fp long, rep long"), 2, 3, hot, scratch)
    got = {r["v"]: r["component"] for r in components(spark, edges).collect()}
    root = list(range(len(fps)))
    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 2:
                a, b = root[i], root[j]
                root = [min(a, b) if r in (a, b) else r for r in root]
    assert {i: got.get(i, i) for i in range(len(fps))} == dict(enumerate(root))


def test_simhash_awkward(spark, awkward, empty):
    rows = simhash.near_duplicates(awkward).collect()
    assert collections.Counter((r["id"], r["fp"] & (1 << 64) - 1) for r in rows) == collections.Counter((i, _fingerprint(t or "")) for i, t, *_ in AWKWARD)
    assert simhash.near_duplicates(empty).count() == 0


def test_drop_near_duplicates(spark, awkward, empty):
    kept = resemblance.drop_near_duplicates(awkward)
    assert kept.columns == awkward.columns and sorted(r["doc_id"] or -1 for r in kept.collect()) == [-1, 1, 3, 4, 6]
    assert resemblance.drop_near_duplicates(empty).count() == 0


@pytest.mark.parametrize("options", [{}, {"broadcast_keys": 0}, {"keep_first": True}])
def test_line_dedup(spark, options):
    rng = random.Random(5)
    rows = [(i, "\n".join(rng.choice(["Menu ", "menu", "a b", f"own {i}", "", "\t", "É"]) for _ in range(rng.randrange(5)))) for i in range(40)] + [(50, None)]
    out = {r["doc_id"]: r for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), min_docs=10, **options).collect()}
    lower = str.maketrans(linededup.UPPER, linededup.LOWER)
    key = lambda line: line.strip(linededup.SPACE).translate(lower)
    seen = collections.Counter(k for _, t in rows for k in {key(x) for x in (t or "").split("\n")} if k)
    kept_somewhere = collections.Counter()
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if seen[key(x)] < 10 or not key(x)]
        if options.get("keep_first"):
            kept_somewhere.update({key(x) for x in out[i]["kept_text"].split("\n") if seen[key(x)] >= 10})
        else:
            assert (out[i]["n_lines"], out[i]["n_dropped"], out[i]["kept_text"]) == (len(lines), len(lines) - len(kept), "\n".join(kept))
    assert all(n == 1 for n in kept_somewhere.values())


def test_language_codes_and_nulls(spark, awkward):
    code = langid.codewords(4)
    assert code.shape == (4, 7) and min((code[i] != code[j]).sum() for i in range(4) for j in range(i)) == 4
    model = langid.LanguageModel.fit(["the cat and the dog"] * 3 + ["der hund und die katze"] * 3, ["en"] * 3 + ["de"] * 3)
    assert model.predict("the dog and the cat")[0] == "en" and model.predict("und der hund")[0] == "de"
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in langid.identify(awkward, model).collect()}
    assert got[1] == got[2] == ("und", 0.0) and all(0 <= s <= 1 for _, s in got.values())


def test_deobfuscation():
    words = "idiot moron scum stupid pathetic clown loser the and of trash other people some thing".split() * 200
    model = toxicity.CharModel(toxicity.trigram_counts([" ".join(words)]))
    restore = toxicity.Restorer(model).token_words
    assert all(w in restore(t) for t, w in {"m0r0n": "moron", "$cum": "scum", "idi0t": "idiot", "p@thetic": "pathetic", "stuuupid": "stupid", "cl0wn!!": "clown"}.items())
    assert "idiot" in toxicity.Restorer(model).features_of("you i d i o t you") and toxicity.Restorer(model).features_of(None) == set()


def test_toxicity_without_labels(spark, awkward):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    chars, model = toxicity.train(awkward.select("doc_id", "text"), labels)
    scored = toxicity.score_documents(awkward, chars, model).collect()
    assert len(scored) == len(AWKWARD) and all(r["score"] < 0.5 for r in scored)


def test_extraction():
    page = '<html><nav><a href="/a">Home</a></nav><div class="cookie-notice">We use cookies here.</div><article><h1>Title &amp; more</h1><p>A long enough  sentence about\n things that matter here.<br><p>Short</p></article><footer>&copy; x</footer>'
    assert htmltext.extract(page) == "Title & more\nA long enough sentence about things that matter here.\nShort"
    assert htmltext.extract(None) == htmltext.extract("") == htmltext.extract("<script>x") == ""


def test_min_cut_is_minimal():
    rng = random.Random(6)
    for _ in range(200):
        n = rng.randrange(1, 7)
        odds = [rng.uniform(-2, 2) for _ in range(n)]
        edges = {(i, j): rng.uniform(0, 2) for i in range(n) for j in range(i) if rng.random() < 0.6}

        def cost(side):
            return sum(max(o, 0) if not s else max(-o, 0) for o, s in zip(odds, side)) + sum(c for (i, j), c in edges.items() if side[i] != side[j])

        assert cost(htmltext.min_cut(odds, edges)) <= min(cost([bool(m >> i & 1) for i in range(n)]) for m in range(1 << n)) + 1e-9

def test_resembling_against_brute_force(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    found = {r["id"]: r["component"] for r in resemblance.resembling(docs).collect()}
    sets = {r["doc_id"]: set(simhash.shingles(r["text"], 5)) for r in docs.collect()}
    parent = {d: d for d in sets}

    def root(d):
        while parent[d] != d:
            d = parent[d]
        return d

    ids = sorted(sets)
    certain = []
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            small, large = sorted((len(sets[a]), len(sets[b])))
            if small < 0.8 * large:
                continue
            both = len(sets[a] & sets[b])
            share = both / (small + large - both) if large else 1.0
            if share >= 0.8:
                parent[max(root(a), root(b))] = min(root(a), root(b))
            if share >= 0.9:
                certain.append((a, b))
    assert found.keys() == sets.keys()
    assert all(found[a] == found[b] for a, b in certain)
    assert all(root(d) == root(found[d]) for d in ids)  # nothing is merged that the exact links do not connect


def test_verified_pairs_repeated_rows(spark, tmp_path):
    words = [f"w{i}" for i in range(40)]
    rows = [(1, " ".join(words)), (1, " ".join(words)), (2, " ".join([*words[:-2], "x", "y"])), (3, " ".join([*words[:-9], *"abcdefghi"])), (4, None), (5, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    asked = spark.createDataFrame([(1, 2), (1, 3), (4, 5)], "a long, b long")
    got = resemblance.verified_pairs(asked, docs, "doc_id", "text", 0.8, 5, 42, resemblance.Scratch(spark, "test")).collect()
    assert [tuple(r) for r in got] == [(1, 2)]


def test_trigram_blocks_are_exact():
    text = "Ein Wort, zwei Wörter: größer; naïve café 12 x"
    whole = toxicity.trigram_counts([text])
    assert all((toxicity.trigram_counts([text], block=b) == whole).all() for b in (1, 3, 7))


def test_resembling_repeated_passage(spark):
    rng = random.Random(8)
    once = " ".join(f"w{rng.randrange(900)}" for _ in range(300))
    rows = [(1, once), (2, f"{once} {once}"), (3, " ".join([once] * 5)), (4, "a b c d e " * 40), (5, "a b c d e " * 90)]
    got = {r["id"]: r["component"] for r in resemblance.resembling(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4}


def _groups_by_all_pairs(texts, similarity=0.8):
    sets = {i: set(simhash.shingles(t, 5)) for i, t in texts}
    root = {i: i for i in sets}
    for i in sets:
        for j in sets:
            if i < j and len(sets[i] & sets[j]) >= similarity * len(sets[i] | sets[j]) - 1e-9 and root[i] != root[j]:
                low, high = sorted((root[i], root[j]))
                root = {k: low if r == high else r for k, r in root.items()}
    return root


def _resembling_groups(spark, rows):
    return {r["id"]: r["component"] for r in resemblance.resembling(spark.createDataFrame(rows, "doc_id long, text string")).collect()}


def test_resembling_crowded_keys(spark):
    rng = random.Random(9)
    passage = [f"p{i}" for i in range(80)]
    texts = []
    for _ in range(60):  # a passage in all of them, and the rest in pairs
        own = [f"w{rng.randrange(10**6)}" for _ in range(50)]
        other = list(own)
        for at in (10, 25, 48):
            other[at] = f"w{rng.randrange(10**6)}"
        texts += [passage + own, passage + other]
    for _ in range(80):  # near copies that are not all near each other
        copy = list(passage)
        for _ in range(rng.randrange(4)):
            copy[rng.randrange(80)] = f"x{rng.randrange(9)}"
        texts.append(copy)
    rng.shuffle(texts)
    rows = [(i, " ".join(t)) for i, t in enumerate(texts)]
    want = _groups_by_all_pairs(rows)
    assert len(set(want.values())) > 60
    assert _resembling_groups(spark, rows) == want


def test_resembling_short_texts_at_the_limit(spark):
    rng = random.Random(10)
    rows = []
    for i in range(0, 120, 2):  # 4 of 5 shingles, 8 of 10
        words = [f"w{rng.randrange(10**6)}" for _ in range(rng.choice((8, 12)))]
        rows += [(i, " ".join(words)), (i + 1, " ".join([*words, *("end again".split()[: len(words) // 6])]))]
    assert _resembling_groups(spark, rows) == _groups_by_all_pairs(rows) == {i: i - i % 2 for i, _ in rows}


def test_deobfuscation_of_any_length():
    words = "you are an idiot moron scum stupid pathetic clown loser the and of trash other people some thing".split() * 200
    restorer = toxicity.Restorer(toxicity.CharModel(toxicity.trigram_counts([" ".join(words)])))
    for token in ("m" + "o" * 60 + "ron", "some-other-people.and-the-thing/m0r0n/of-other-people", "the-people-m.0.r.0.n-some-thing-and-other-people", "other_thing_" * 9 + "m0r0n_the"):
        assert len(token) > 40 and "moron" in restorer.features_of(token), token
    letters = "you are an idiot and the other people are some trash and pathetic loser".split()
    for gap in (" ", "  "):
        assert {"idiot", "trash", "pathetic", "loser"} <= restorer.features_of(gap.join(" ".join(w) for w in letters)), gap
    assert "moron" in restorer.features_of("ab-" * 20_000 + "m0r0n")


def test_deobfuscation_of_other_alphabets_and_doubles():
    words = "you are an idiot moron scum stupid pathetic clown loser the and of trash other people some thing little letter".split() * 200
    model = toxicity.CharModel(toxicity.trigram_counts([" ".join(words)]))
    restorer = toxicity.Restorer(model, frozenset(["idiot", "moron", "^path", "loser"]))
    for text, feature in {"iidiot": "idiot", "moronn": "moron", "іdіоt": "idiot", "ｉｄｉｏｔ": "idiot", "Ｍｏｒｏｎ": "moron", "lоsеr!": "loser", "ppathetically": "^path", "y o u a r e a n i d i o t": "idiot", "і d і о t": "idiot"}.items():
        assert feature in restorer.features_of(text), text
    assert restorer.features_of("little letter people") == set()


def test_plain_words_are_not_taken_apart(monkeypatch):
    model = toxicity.CharModel(toxicity.trigram_counts(["some plain words of a text"]))
    taken = []
    whole = toxicity.Restorer.token_words
    monkeypatch.setattr(toxicity.Restorer, "token_words", lambda self, token: taken.append(token) or whole(self, token))
    found = toxicity.Restorer(model, frozenset({"idiot", "^moro"})).features_of("plain words, an idiot and moron moronic 1d1ot iddiot соme été")
    assert found == {"idiot", "^moro"} and set(taken) == {"words,", "idiot", "moron", "moronic", "1d1ot", "iddiot", "соme", "come"}


def test_near_duplicates_go_by_fingerprints_first(spark, monkeypatch):
    """The query's links hold in the pipeline too, and what they miss is still found."""
    rng, seen = random.Random(8), []
    base = " ".join(f"w{rng.randrange(10**6)}" for _ in range(60))
    rows = [(3, base), (7, base + " tail"), (9, base.upper()), (11, "quite another text"), (None, base)]
    whole = resemblance.near_duplicates
    monkeypatch.setattr(resemblance, "near_duplicates", lambda *a: seen.append(1) or whole(*a))
    kept = resemblance.drop_near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 3, 11] and seen


def test_resembling_shared_passages_meet_seldom(spark, monkeypatch):
    """Texts that share a few rare shingles and are not alike are no pairs of the last step; those that are alike are."""
    rng, found = random.Random(12), []
    word = lambda: f"w{rng.randrange(10**7)}"
    passages = [[word() for _ in range(6)] for _ in range(12)]  # two shingles each
    rows = [(i, " ".join(w for k in range(4) for w in [*[word() for _ in range(100)], *passages[(i + k) % 12]])) for i in range(72)]
    near = rows[7][1].split()
    for at in range(20, 400, 45):
        near[at] = word()
    rows.append((100, " ".join(near)))
    close = resemblance._close_pairs
    monkeypatch.setattr(resemblance, "_close_pairs", lambda *a: found.append(close(*a)) or found[-1])
    assert _resembling_groups(spark, rows) == _groups_by_all_pairs(rows) == {i: 7 if i == 100 else i for i, _ in rows}
    assert found[0].count() < 300  # of 2628 pairs, most of which share a passage


def test_pairs_travel_with_short_prefixes(spark, monkeypatch):
    # two shingles of one set look equal by their last 16 bits, and so do two of different sets
    sets = {1: [1, 1 + (1 << 16), 7, 9], 2: [1, 1 + (1 << 16), 7, 11], 3: [1 + (1 << 17), 20, 21, 22]}
    first = spark.createDataFrame([(i, 4, s, 0) for i, s in sets.items()], "id long, n long, prefix array<bigint>, w long")
    pairs = spark.createDataFrame([(1, 2), (1, 3)], "a long, b long")
    plans, save = [], resemblance.Scratch.save
    monkeypatch.setattr(resemblance.Scratch, "save", lambda self, df: plans.append(df._jdf.queryExecution().optimizedPlan().schema().simpleString() + df._jdf.queryExecution().analyzed().toString()) or save(self, df))
    got = resemblance._by_prefixes(pairs, first, 0.6, resemblance.Scratch(spark, "test")).collect()
    assert [tuple(r) for r in got] == [(1, 2)]  # they share 3 of 5
    assert "as smallint" in plans[-1] and "array_intersect(a_short" in plans[-1]
