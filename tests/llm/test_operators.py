"""The training-data operators against brute force, on hostile small inputs: nulls, empties, ties, repeats, clashing names."""

import base64
import hashlib
import math
import random

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from pinflow.llm import ann, bpe, exact_dedup, langid, minhash, mixing, sharding, suffix_dedup, token_counts, toxicity
from pinflow.llm.graph import components

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, shard int, mix_p double, `a.b` string"
PATH = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def words(rng, n, vocabulary=400):
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(7)
    texts = [" ".join(words(rng, rng.randint(1, 60))) for _ in range(40)]
    base = words(rng, 80)
    for _ in range(30):
        own = list(base)
        for _ in range(rng.randint(0, 4)):
            own[rng.randrange(80)] = f"x{rng.random()}"
        texts.append(" ".join(own))
    texts += ["SAME text Here", "same TEXT here", "same text here", "", None, " \t\n", "é" * 60, "long " * 4000, "a b c d", "A B C D", "It's we'll  \n\n x1 ²½ 中文's"]
    langs, sources = ["en", "de", None], ["s1", "s2", None]
    out = [(i, t, langs[i % 3], sources[i % 2 * (i % 3)], None if t is None else len(t), 1, 0.5, "z") for i, t in enumerate(texts)]
    return out + [(None, "same text here", None, None, None, 1, 0.5, "z"), out[0]]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def test_exact_dedup(docs, rows, empty):
    groups = {}
    for r in rows:
        groups.setdefault(lower(r[1]), []).append(r[0])
    got = exact_dedup.exact_groups(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        own = next(g for t, g in groups.items() if hashlib.sha256(t.encode()).hexdigest() == r["text_sha256"])
        assert r["group_size"] == len(own) and r["keep_id"] == max(x for x in own if x is not None) and r["kept"] == (r["doc_id"] == r["keep_id"])
    small = exact_dedup.exact_groups(docs, keep="smallest").filter("text_sha256 = sha2('same text here', 256)").collect()
    assert {r["keep_id"] for r in small} == {70}
    assert exact_dedup.exact_groups(empty).count() == 0


def shingles(t):
    ws = lower(t).replace("\t", " ").replace("\n", " ").replace("\r", " ").replace("\x0b", " ").replace("\x0c", " ").split(" ")
    ws = [w for w in ws if w]
    return {tuple(ws[i : i + 5]) for i in range(max(1, len(ws) - 4))} if ws else set()


def near_truth(rows):
    sets = {r[0]: shingles(r[1]) for r in rows if r[0] is not None}
    label = {i: i for i in sets}
    changed = True
    while changed:
        changed = False
        for a in sets:
            for b in sets:
                if a < b and sets[a] and label[a] != label[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                    lo, hi = sorted((label[a], label[b]))
                    label = {i: lo if x == hi else x for i, x in label.items()}
                    changed = True
    return sets, label


def test_near_duplicates(docs, rows, empty):
    sets, label = near_truth(rows)
    got = minhash.near_duplicates(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        if r["doc_id"] is not None:
            assert (r["n_shingles"], r["component_id"], r["kept"]) == (len(sets[r["doc_id"]]), label[r["doc_id"]], r["doc_id"] == label[r["doc_id"]])
    assert minhash.near_duplicates(empty).count() == 0


def test_crowded_lists_lose_no_link(docs, rows):
    """With a crowd limit of 3, lists are rebuilt from full sets and met by hubs in turns; components stay the same."""
    sets, label = near_truth(rows)
    reps = minhash.sketches(docs, "doc_id", "text").filter("doc_id is not null and n_shingles > 0").dropDuplicates(["doc_id"])
    found = {r["node"]: r["component"] for r in minhash.near_links(docs, reps.select("doc_id", "n_shingles", "sketch"), crowd=3).collect()}
    for i, s in sets.items():
        assert found.get(i, i) == label[i]


def test_components(spark):
    rng = random.Random(3)
    pairs = [(i, i + 1) for i in range(40)] + [(100 + rng.randrange(30), 100 + rng.randrange(30)) for _ in range(25)]
    label = {x: x for p in pairs for x in p}
    for _ in range(100):
        for a, b in pairs:
            label[a] = label[b] = min(label[a], label[b])
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(pairs, "a bigint, b bigint")).collect()}
    assert all(got.get(x, x) == c for x, c in label.items())


def suffix_truth(rows):
    data = [(i, (t or "").encode()) for i, t in rows]
    first = {}
    for i, t in data:
        if i is not None:
            for p in range(len(t) - 49):
                first[t[p : p + 50]] = min(i, first.get(t[p : p + 50], i))
    out = []
    for i, t in data:
        gone = bytearray(len(t))
        for p in range(len(t) - 49):
            if i is not None and first[t[p : p + 50]] < i:
                gone[p : p + 50] = b"\1" * 50
        kept = bytes(b for b, g in zip(t, gone) if not g)
        spans = sum(1 for p in range(len(t)) if gone[p] and not (p and gone[p - 1]))
        out.append((i, len(t), sum(gone), spans, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


@pytest.mark.parametrize("crowd", [1, 50_000])
def test_suffix_dedup(spark, rows, empty, crowd):
    rng = random.Random(5)
    base = "".join(rng.choice("abcdef ") for _ in range(1500))
    extra = []
    for i in range(25):
        a, b = rng.randint(0, 1200), rng.randint(0, 1300)
        extra.append((500 + i, base[a : a + rng.randint(20, 300)] + "".join(rng.choice("xyz") for _ in range(rng.randint(0, 60))) + base[b : b + 90]))
    extra += [(600, "q" * 300), (601, "q" * 49 + "!"), (602, "q" * 70), (603, base[:50]), (604, base[1:51])]
    data = [(r[0], r[1]) for r in rows] + extra
    df = spark.createDataFrame(data, "doc_id bigint, text string").repartition(4)
    got = sorted((tuple(r) for r in suffix_dedup.dedup_report(df, crowd=crowd).collect()), key=str)
    assert got == suffix_truth(data)
    assert suffix_dedup.dedup_report(empty).count() == 0


@pytest.mark.parametrize("letters,groups", [(2, 3), (1, 5), (26, 1), (256, 2)])
def test_suffix_order_is_sorted(letters, groups):
    """The order that quicksort and tries give is the order of the bytes, and equal strings stand together."""
    rng = np.random.default_rng(letters)
    data = rng.integers(0, letters, 4000).astype(np.uint8) if letters == 256 else rng.integers(97, 97 + letters, 4000, dtype=np.uint8)
    data[1000:1400] = data[200:600]
    data[3000:3060] = 255
    data[3100:3160] = 0
    starts, group = np.arange(3900), (np.arange(3900) % groups - 1).astype(np.int64)
    order, fresh = suffix_dedup.suffix_order(data, starts, group)
    keys = [(group[i], data[starts[i] : starts[i] + 50].tobytes()) for i in order]
    assert sorted(order.tolist()) == list(range(3900)) and keys == sorted(keys)
    assert fresh.tolist() == [True] + [a != b for a, b in zip(keys, keys[1:])]
    none = np.empty(0, dtype=np.int64)
    assert len(suffix_dedup.suffix_order(data, none, none)[0]) == 0


def test_vantage_trees(spark):
    rng = np.random.default_rng(1)
    v = [(i, rng.normal(size=8).tolist()) for i in range(600)]
    v += [(600 + i, v[3][1]) for i in range(40)] + [(700, None), (701, [0.0] * 8), (702, [math.nan] * 8), (703, [1.0, None] * 4), (704, [math.inf] * 8), (750, [1.0, 2.0]), (751, [2.0, 4.1])]
    df = spark.createDataFrame(v, "vec_id bigint, embedding array<double>").repartition(3)
    got = {}
    for r in ann.nearest(df, df.filter("vec_id % 50 = 0"), shard_rows=100).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    fine = [(i, np.array(x, dtype=float)) for i, x in v if x and all(y is not None and math.isfinite(y) for y in x) and any(x)]
    for q, x in fine:
        if q % 50 == 0:
            others = [(i, float(ann.cosine(x[None], y[None])[0])) for i, y in fine if i != q and len(y) == len(x)]
            assert got[q] == sorted(others, key=lambda t: (-t[1], t[0]))[:5]
    assert 700 not in got and [x[0] for x in got[750]] == [751]


def test_relaxed_search_keeps_recall():
    rng = np.random.default_rng(4)
    centres = rng.normal(size=(20, 16))
    x = centres[rng.integers(0, 20, 4000)] + 0.3 * rng.normal(size=(4000, 16))
    x /= np.linalg.norm(x, axis=1)[:, None]
    tree = ann.VantageTree(x)
    exact = [set(np.argsort(-(x @ q))[:5].tolist()) for q in x[:60]]
    found, all_seen = tree.search(x[:60], 13, 1.0)
    order = lambda q, f: set(sorted(f.tolist(), key=lambda r: -(x[r] @ q))[:5])
    assert all(order(q, f) == e for q, f, e in zip(x[:60], found, exact))
    found, seen = tree.search(x[:60], 13, 2.0)
    recall = np.mean([len(order(q, f) & e) / 5 for q, f, e in zip(x[:60], found, exact)])
    assert recall >= 0.9 and seen.mean() < all_seen.mean() < 4000


def test_sharding(docs, rows, empty):
    got = sharding.external_shuffle(docs, 7).select("doc_id", "text", "shard", "slot", "mix_p", "`a.b`").collect()
    assert sorted((str(r["doc_id"]), str(r["text"])) for r in got) == sorted((str(r[0]), str(r[1])) for r in rows)
    by = {}
    for r in got:
        by.setdefault(r["shard"], []).append(r["slot"])
    assert set(by) == set(range(7)) and all(sorted(s) == list(range(len(s))) for s in by.values())
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    again = {(r["doc_id"], r["text"], r["shard"], r["slot"]) for r in sharding.external_shuffle(docs.repartition(5), 7).collect()}
    assert {(r["doc_id"], r["shard"], r["slot"]) for r in got if r["doc_id"] != 0} == {(r[0], r[2], r[3]) for r in again if r[0] != 0}
    assert sharding.shard_report(empty).count() == 0
    ids = [r["doc_id"] for r in sorted(got, key=lambda r: (r["shard"], r["slot"])) if r["doc_id"] is not None]
    assert ids != sorted(ids)


def test_bpe_is_tiktoken(docs, rows, empty):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(PATH, "rb"))}
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    rng = random.Random(1)
    letters = list("stmdrvle''' \n\t a1!é中²\U0001f600ſİ")
    texts = ["".join(rng.choice(letters) for _ in range(rng.randint(0, 14))) for _ in range(8000)]
    texts += ["ab" * 500 + "etaoin" * 100, "a" * 3000, "!" * 4000, " " * 3000, "\x1c\x1f x", ""]
    tool = bpe.codec(PATH)
    for t, ids in zip(texts, tool.encode(texts)):
        assert ids.tolist() == enc.encode_ordinary(t) and tool.decode(ids) == t.encode()
    want = sorted((str(r[0]), len(i := enc.encode_ordinary(r[1] or "")), hashlib.sha256(np.array(i, dtype="<u4").tobytes()).hexdigest(), hashlib.sha256((r[1] or "").encode()).hexdigest()) for r in rows)
    assert sorted((str(r[0]), *r[1:]) for r in bpe.encoding_report(docs, PATH).collect()) == want
    encoded = bpe.encode_documents(docs, PATH)
    assert {bytes(r["data"]) for r in bpe.decode_documents(encoded, PATH).collect()} == {(r[1] or "").encode() for r in rows}
    for r in encoded.collect():
        assert r["offsets"][0] == 0 and len(r["offsets"]) == len(r["ids"]) + 1
    assert bpe.encoding_report(empty, PATH).count() == 0


def test_scan_is_the_automaton():
    rng = np.random.default_rng(0)
    classes = rng.integers(0, bpe.STATES, 3000).astype(np.uint8)
    state, want = bpe.S_SEP, []
    for c in classes:
        state = bpe._step(state, int(c))
        want.append(state)
    for block in (16, 256, 4096):
        assert bpe.scan_states(classes, block).tolist() == want


@pytest.mark.parametrize("block", [8, 65536])
def test_token_counts(docs, rows, empty, block):
    tool = bpe.codec(PATH)
    want = sorted((str(r[0]), len(tool.encode([r[1] or ""])[0])) for r in rows)
    got = token_counts.count_report(docs, PATH, block).collect()
    assert sorted((str(r["doc_id"]), r["n_tokens"]) for r in got) == want
    assert token_counts.count_report(empty, PATH).count() == 0


def test_separators_across_blocks(spark):
    s = token_counts.SEPARATOR
    flat = np.array([1, 2, s, s, 3, 4, 5, 6, 7, 8, 9, s, 1, 1], dtype="<u2")
    blocks = [(0, i, flat[4 * i : 4 * i + 4].tobytes()) for i in range(4)] + [(1, 0, b"")]
    files = spark.createDataFrame([(f, i, bytearray(b)) for f, i, b in blocks], "file_id int, number bigint, data binary")
    got = token_counts.stitch(token_counts.scan_separators(files, block=4)).orderBy("ordinal").collect()
    assert [(r["ordinal"], r["n_tokens"], r["closed"]) for r in got] == [(0, 2, True), (1, 0, True), (2, 7, True), (3, 2, False)]


def test_language(spark, docs, rows, empty):
    rng = random.Random(2)
    vocab = {"en": ["the", "house", "water", "thing", "other"], "de": ["das", "haus", "wasser", "schön", "über"], "fr": ["le", "maison", "été", "chose", "autre"]}
    data = [(i, " ".join(rng.choice(vocab[lang]) for _ in range(12)), lang) for i in range(300) for lang in [list(vocab)[i % 3]]]
    df = spark.createDataFrame(data, "doc_id bigint, text string, lang string")
    got = langid.language_report(df).join(df, "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    assert held and all(r["lang"] == r["lang_pred"] and 0 <= r["score"] <= 1 for r in got)
    model = langid.fit(df)
    assert model.predict("wassers schönes")[0] == "de" and model.predict("")[0] == model.predict(None)[0] == model.predict("12 !?")[0] == "und"
    assert model.predict("中")[1] == pytest.approx(1 / 3)
    for text in ("²½ Ⅷ", "①②", "_ 3", "\u0301", "٣"):
        assert model.predict(text) == ("und", 0.0)
    assert langid.words_of("ab²cd Ⅷx") == ["ab", "cd", "x"] and langid.words_of("x" * 300) == ["x" * 300]
    assert langid.language_report(docs).count() == len(rows)
    assert langid.language_report(empty).count() == 0
    kept = langid.keep_identified(docs)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.filter("text is null or trim(text) = ''").collect()} == set()


def test_language_held_out(spark, sf):
    d = sf.replace("0.001", "0.01")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    got = langid.language_report(docs).filter("held_out").join(docs.select("doc_id", "lang"), "doc_id")
    assert got.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97


def test_toxicity(spark, docs, rows, empty):
    grammar = toxicity.Grammar({"idiot": 5.0}, {"achlich": 4.0})
    base = grammar.score("a plain sentence")
    assert grammar.score("you are an idiot") > grammar.score("idiot") > grammar.score("he is not an idiot") > base
    assert grammar.score("they said idiot.") < grammar.score("word word idiot.") and grammar.score("achlichung") > base
    assert grammar.score(None) == grammar.score("") == pytest.approx(base)
    rng = random.Random(8)
    data = [(i, " ".join(words(rng, 30) + (["grobian"] * 3 if i % 4 == 0 else []))) for i in range(600)]
    df = spark.createDataFrame(data, "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(600)] + [(1, 0), (None, 1), (2, None)], "doc_id bigint, toxic int")
    got = {r["doc_id"]: r for r in toxicity.toxicity_report(df, labels).collect()}
    assert all(r["predicted"] == int(i % 4 == 0) for i, r in got.items() if r["held_out"])
    assert toxicity.toxicity_report(docs, labels.limit(0)).count() == len(rows)
    assert toxicity.toxicity_report(empty, labels).count() == 0


def test_toxicity_held_out(spark, sf):
    d = sf.replace("0.001", "0.1")
    labels = spark.read.parquet(f"{d}/labels.parquet")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    got = toxicity.toxicity_report(docs, labels).filter("held_out").join(labels, "doc_id").collect()
    bad, good = [r["score"] for r in got if r["toxic"]], [r["score"] for r in got if not r["toxic"]]
    auc = np.mean([np.mean([b > g for b in bad]) + 0.5 * np.mean([b == g for b in bad]) for g in good])
    assert auc > 0.9


def test_transducers_compose():
    table, factor = toxicity.compose(toxicity.INSULTING, toxicity.THREATENING, toxicity.AIMED, toxicity.NEGATED, toxicity.REPORTED)
    state = 0
    for x in (toxicity.TARGET, toxicity.NEGATION, toxicity.PLAIN):
        state = table[state][x]
    assert factor[state][toxicity.INSULT] == pytest.approx(0.3 * 1.5)
    assert factor[table[state][toxicity.INSULT]][toxicity.INSULT] == pytest.approx(1.25 * 0.3 * 1.5)
    calm, armed = table[state][toxicity.END], table[0][toxicity.INTENT]
    assert factor[calm][toxicity.INSULT] == 1.0 and factor[calm][toxicity.THREAT] == pytest.approx(0.2) and factor[armed][toxicity.THREAT] == 1.0
    assert factor[table[armed][toxicity.TARGET]][toxicity.THREAT] == 1.5 and factor[table[armed][toxicity.REPORT]][toxicity.THREAT] == 0.5


def test_grammar_is_the_transducers_run_one_by_one():
    """Scores of matched clauses by the composed machine and by stepping each transducer on its own."""
    rng = random.Random(12)
    parts = [toxicity.INSULTING, toxicity.THREATENING, toxicity.AIMED, toxicity.NEGATED, toxicity.REPORTED]
    grammar = toxicity.Grammar({"grob": 3.0}, {})
    pool = ["idiot", "grob", "kill", "will", "you", "not", "said", "word", "other", ".", "!"]
    for _ in range(200):
        tokens = [rng.choice(pool) for _ in range(rng.randrange(30))]
        total = top = clause = matched = 0.0
        states, hit = [0] * len(parts), False
        for t in [*tokens, "."]:
            x, weight = grammar.symbol(t)
            if x in (toxicity.INSULT, toxicity.THREAT):
                hit = True
                for p, s in zip(parts, states):
                    weight *= p.passes(s, x)
                clause += weight
            states = [p.step(s, x) for p, s in zip(parts, states)]
            if x == toxicity.END:
                total, top, matched = total + clause, max(top, clause), matched + hit
                clause, hit = 0.0, False
        got = grammar.features(" ".join(tokens))
        assert got[0] == pytest.approx(math.log1p(total)) and got[1] == pytest.approx(min(top, 12.0)) and got[3] == pytest.approx(math.log1p(matched))


def test_mixing(spark, docs, rows, empty):
    data = [(s, l, float(n)) for s, l, n in (("a", "en", 900), ("a", "de", 60), ("b", "en", 30), ("b", "de", 10))]
    cells = spark.createDataFrame(data, "s string, l string, mix_n double")
    targets = {"s": spark.createDataFrame([("a", 0.5), ("b", 0.5)], "s string, share double"), "l": spark.createDataFrame([("en", 0.7), ("de", 0.3)], "l string, share double")}
    fitted = mixing.rake(cells, ["s", "l"], targets).collect()
    share = lambda k, v: sum(r["mix_n"] * r["mix_g"] for r in fitted if r[k] == v)
    assert share("s", "a") == pytest.approx(0.5, abs=1e-6) and share("l", "de") == pytest.approx(0.3, abs=1e-6)
    kept = mixing.calibrate(mixing.rake(cells, ["s", "l"], targets), 0.3).collect()
    assert sum(r["mix_n"] * r["mix_p"] for r in kept) == pytest.approx(300, rel=1e-6) and max(r["mix_p"] for r in kept) <= 1
    report = mixing.mixing_report(docs).collect()
    assert len(report) == len(rows) and all(0 <= r["keep_probability"] <= 1 for r in report)
    assert mixing.keep_mixed(docs).columns == docs.columns
    assert mixing.mixing_report(empty).count() == 0


def test_mixing_reaches_its_targets(spark):
    """Small groups would need a probability above one: shares of drawn tokens still meet the tempered targets."""
    data = [(i, "w w w w" + (" a@b" if i % 50 == 0 else " w"), "de" if i % 20 == 3 else "en", "b" if i % 10 == 7 else "a") for i in range(6000)]
    docs = spark.createDataFrame(data, "doc_id bigint, text string, lang string, source string")
    plan = mixing.mixing_plan(docs, {"s": F.col("source"), "l": F.col("lang"), "t": mixing.surface_topic(F.col("text"))}).collect()
    assert max(r["mix_w"] for r in plan) > 1.5
    got = mixing.keep_mixed(docs).collect()
    times = {}
    for r in got:
        times[r["doc_id"]] = times.get(r["doc_id"], 0) + 1
    assert times == {r["doc_id"]: r["copies"] for r in mixing.mixing_report(docs).collect() if r["kept"]}
    assert len(times) == pytest.approx(0.8 * 6000, rel=0.03)
    for dim, of in (("s", lambda r: r["source"]), ("l", lambda r: r["lang"]), ("t", lambda r: "contact" if "@" in r["text"] else "prose")):
        tokens = {}
        for r in plan:
            tokens[r[dim]] = tokens.get(r[dim], 0) + r["mix_n"]
        for v, n in tokens.items():
            target = n**0.7 / sum(x**0.7 for x in tokens.values())
            assert sum(r["mix_n"] * r["mix_w"] for r in plan if r[dim] == v) / sum(r["mix_n"] * r["mix_w"] for r in plan) == pytest.approx(target, abs=1e-6)
            assert sum(of(r) == v for r in got) / len(got) == pytest.approx(target, abs=0.01)


@pytest.mark.parametrize("name", ["op1_mixing", "op2_minhash", "op3_suffix_dedup", "op4_vantage_ann", "op9_exact_dedup"])
def test_queries_match_duckdb(spark, sf, name):
    import duckdb

    from pinflow.llm import registry

    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    want = con.execute(registry.ORACLES[name]).df()
    cols = sorted(want.columns)
    got = registry.QUERIES[name](spark, sf).toPandas()[cols]
    plain = lambda df: sorted(tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in df.itertuples(index=False, name=None))
    assert plain(got) == plain(want[cols])


def test_one_direction_at_many_scales(spark):
    """Sixty different vectors of one direction have equal cosines: the smallest ids are the answer."""
    rows = [(i, [x * 2.0 ** ((i * 7) % 60 - 30) for x in (0.3, -0.4, 0.5)]) for i in range(60)] + [(100 + i, [1.0, float(i), 0.0]) for i in range(20)]
    table = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>")
    found = {}
    for r in ann.nearest(table, table.filter("vec_id < 60")).orderBy("query_id", "rank").collect():
        found.setdefault(r["query_id"], []).append(r["vec_id"])
    assert found == {i: [j for j in range(6) if j != i][:5] for i in range(60)}


def test_ids_with_several_texts(spark):
    """Rows are judged one by one: no text is lost with an id that is dropped for another text of it."""
    data = [(1, "a"), (1, "b"), (2, "b"), (None, "b"), (None, "z"), (None, "Z")]
    docs = spark.createDataFrame([(i, t, "x") for i, t in data], "doc_id bigint, text string, __id string")
    assert sorted(map(tuple, exact_dedup.keep_one(docs).select("doc_id", "text").collect()), key=str) in ([(1, "a"), (2, "b"), (None, t)] for t in "zZ")
    base, other = [f"w{i}" for i in range(60)], [f"v{i}" for i in range(60)]
    near = " ".join([*base[:59], "end"])
    rows = [(1, " ".join(base)), (3, near), (3, " ".join(other)), (4, " ".join([*other[:59], "end"])), (4, "alone"), (5, "ALONE")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    kept = sorted(map(tuple, minhash.keep_one(df).collect()))
    assert kept == sorted([rows[0], rows[2], rows[4]])
    got = {(r["doc_id"], r["component_id"]) for r in minhash.near_duplicates(df).collect()}
    assert got == {(1, 1), (3, 1), (3, 3), (4, 3), (4, 4), (5, 4)}


def test_self_similar_words_are_told_apart(spark):
    """Two words of 1,024 letters that any polynomial modulo 2**64 joins."""
    word = "a"
    while len(word) < 1024:
        word += "".join("b" if c == "a" else "a" for c in word)
    rows = [(1, word), (2, "".join("b" if c == "a" else "a" for c in word))]
    got = minhash.near_duplicates(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert {(r["doc_id"], r["component_id"], r["class_id"]) for r in got} == {(1, 1, 1), (2, 2, 2)}


def test_mixing_beside_columns_of_its_own_names(docs, rows):
    got = mixing.mix(docs.withColumn("mix_source", F.lit("x")).withColumn("row", F.lit(1)))
    assert got.count() == len(rows) and got.columns.count("mix_p") == 1 and "`a.b`" not in got.columns and "a.b" in got.columns
    assert {r["mix_source"] for r in got.select("mix_source").collect()} == {"s1", "s2", mixing.NONE}
    kept = mixing.keep_mixed(docs.withColumn("row", F.lit(1)))
    assert kept.columns == [*docs.columns, "row"] and {r["mix_p"] for r in kept.collect()} == {0.5}


def test_raking_ends_at_its_residual(spark):
    """One row of arrays and a table of cells give the same factors; targets that can't be met are told by mix_off."""
    rng = random.Random(4)
    cells = spark.createDataFrame([(f"s{i}", f"l{j}", rng.randrange(1, 500)) for i in range(9) for j in range(7) if rng.random() < 0.8], "s string, l string, mix_n long")
    fits = [mixing.rake(cells, ["s", "l"], narrow=n).collect() for n in (1000, 0)]
    assert all(f[0]["mix_off"] <= mixing.RESIDUAL for f in fits)
    one, two = ({(r["s"], r["l"]): r["mix_g"] for r in f} for f in fits)
    assert one.keys() == two.keys() and all(one[k] == pytest.approx(two[k], rel=1e-6) for k in one)
    odd = spark.createDataFrame([("a", "x", 10), ("b", "y", 10)], "s string, l string, mix_n long")
    share = lambda d, v: spark.createDataFrame(v, f"{d} string, share double")
    for n in (1000, 0):
        off = mixing.rake(odd, ["s", "l"], {"s": share("s", [("a", 0.9), ("b", 0.1)]), "l": share("l", [("x", 0.5), ("y", 0.5)])}, narrow=n).first()["mix_off"]
        assert off == pytest.approx(0.4)


@pytest.mark.parametrize("shard_rows", [7, 100_000])
def test_many_equal_distances(spark, shard_rows):
    """One-hot vectors are all equally far, collinear ones all equally near: ids decide, whatever the tree keeps."""
    hot = [(i, [1.0 if j == i else 0.0 for j in range(64)]) for i in range(64)]
    table = spark.createDataFrame(hot, "vec_id bigint, embedding array<double>").repartition(3)
    got = {(r["query_id"], r["rank"]): r["vec_id"] for r in ann.nearest(table, table, shard_rows=shard_rows).collect()}
    assert got == {(i, n + 1): j for i in range(64) for n, j in enumerate([x for x in range(6) if x != i][:5])}
    line = [(i, [2.0 ** (i % 900 - 450), 0.0, 0.0]) for i in range(1000)]
    table = spark.createDataFrame(line, "vec_id bigint, embedding array<double>").repartition(5)
    got = {(r["query_id"], r["rank"]): r["vec_id"] for r in ann.nearest(table, table.filter("vec_id % 50 = 0"), shard_rows=shard_rows).collect()}
    assert got == {(i, n + 1): j for i in range(0, 1000, 50) for n, j in enumerate([x for x in range(6) if x != i][:5])}


def test_queries_visit_few_shards(spark):
    """On clustered vectors a query's ball meets few cells: what is sent stays far below queries x shards."""
    rng = np.random.default_rng(6)
    centres = rng.normal(size=(30, 16))
    data = [(i, (centres[i % 30] + 0.05 * rng.normal(size=16)).tolist()) for i in range(3000)] + [(4000 + i, centres[0].tolist()) for i in range(900)]
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<double>")
    pivots = {16: ann.unit_rows(centres)}
    cells = {16: (np.ones(30, np.int64), np.zeros(30), np.full(30, 0.2))}
    asked = df.limit(100).select(F.lit(16).alias("dim"), F.col("vec_id").alias("number"), (F.col("vec_id") % 30).cast("int").alias("own"), F.lit(0.1).alias("radius"), F.col("embedding").alias("v"))
    sent = asked.mapInArrow(ann._visits(pivots, cells, 1.0), "dim int, cell int, part int, number bigint, radius double, v array<double>").count()
    assert sent < 100 * 30 / 10
    got = {(r["query_id"], r["rank"]): r["vec_id"] for r in ann.nearest(df, df.filter("vec_id % 500 = 0"), shard_rows=50).collect()}
    for q in range(0, 4900, 500):
        if q < 3000 or q >= 4000:
            v = dict(data)[q]
            score = sorted(((-float(ann.cosine(np.array([v]), np.array([x]))[0]), i) for i, x in data if i != q))[:5]
            assert [got[q, n + 1] for n in range(5)] == [i for _, i in score]
    assert ann.nearest(df.limit(0), df.limit(0)).count() == 0


def test_sharding_by_brute_force(spark, docs, rows):
    """Sizes, checksums and places by a plain replay: buckets by the seeded hash, Fisher-Yates in each, cut at even positions."""
    import zlib

    seed, shards = 11, 7
    key = F.xxhash64(F.lit(seed), F.col("doc_id"), F.xxhash64("text"))
    n = 2 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    found = docs.select("doc_id", "text", F.pmod(key, F.lit(n)).alias("b"), F.xxhash64("text").alias("h")).collect()
    at, want = 0, {}
    for b in range(n):
        own = sorted((r for r in found if r["b"] == b), key=lambda r: (r["doc_id"] is not None, r["doc_id"] or 0, r["h"]))
        for i, j in enumerate(sharding.fisher_yates(len(own), np.random.default_rng([seed, b]))):
            where = (at + i) * shards // len(found)
            want.setdefault((own[j]["doc_id"], own[j]["text"]), []).append((where, at + i - -(-where * len(found) // shards)))
        at += len(own)
    got = {}
    for r in sharding.external_shuffle(docs, shards).collect():
        got.setdefault((r["doc_id"], r["text"]), []).append((r["shard"], r["slot"]))
    assert {k: sorted(v) for k, v in got.items()} == {k: sorted(v) for k, v in want.items()}
    text = {r[0]: r[1] or "" for r in rows if r[0] is not None}
    for r in sharding.shard_report(docs).collect():
        if r["doc_id"] is not None:
            data = text[r["doc_id"]].encode()
            assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(data) + 16, zlib.crc32(data), "rows", None)


def test_one_record_may_be_most_of_a_table(spark):
    data = [(7, "same")] * 6000 + [(100 + i, f"t{i}") for i in range(900)]
    placed = sharding.external_shuffle(spark.createDataFrame(data, "doc_id bigint, text string").repartition(3), 5)
    assert placed.columns == ["doc_id", "text", "shard", "slot"]
    got = placed.collect()
    assert sorted((r["doc_id"], r["text"]) for r in got) == sorted(data) and len({(r["shard"], r["slot"]) for r in got}) == len(data)
    tasks = placed.select(F.spark_partition_id().alias("p")).groupBy("p").count().collect()
    assert max(r["count"] for r in tasks) < 4000


def test_ids_that_do_not_fit_are_an_error(spark):
    docs = spark.createDataFrame([(1, "hello there")], "doc_id bigint, text string")
    with pytest.raises(Exception, match="not below the separator"):
        token_counts.token_files(docs, PATH, separator=5).collect()
    with pytest.raises(ValueError, match="16 bits"):
        token_counts.token_files(docs, PATH, separator=70_000)


@pytest.mark.parametrize("dense", [0, 1 << 20])
def test_lists_meet_in_one_matrix_or_hub_by_hub(monkeypatch, dense):
    """Every pair of different components that is similar enough comes from the lists, from sketches that hold whole sets."""
    monkeypatch.setattr(minhash, "DENSE", dense)
    rng = np.random.default_rng(3)
    base = [rng.choice(10**6, 40, replace=False) for _ in range(4)]
    sets = []
    for d in range(48):
        own = base[d % 4].copy()
        own[: rng.integers(0, 9)] = 10**6 + d
        sets.append(np.unique(own))
    members = {v: sorted({v, *rng.choice(48, 24).tolist()}) for v in range(12)}
    hub = {(v, d): bool(rng.random() < 0.7) for v in members for d in members[v]}
    told = {d: [{"value": v, "is_hub": hub[v, d]} for v in members if d in members[v]] for d in range(48)}
    rows = [(v, 0, role, d, d // 8, len(sets[d]), len(sets[d]), sets[d], told.get(d)) for v in members for role in (0, 1) for d in members[v] if role or hub[v, d]]
    kinds = [minhash.pa.int64(), minhash.pa.int32(), minhash.pa.int32(), *[minhash.pa.int64()] * 4, minhash.pa.list_(minhash.pa.int64()), minhash.pa.list_(minhash.pa.struct([("value", minhash.pa.int64()), ("is_hub", minhash.pa.bool_())]))]
    batch = minhash.pa.RecordBatch.from_arrays([minhash.pa.array([r[i] for r in rows], t) for i, t in enumerate(kinds)], [f"c{i}" for i in range(9)])
    got = [p for out in minhash._meet(75)(iter([batch.slice(i, 31) for i in range(0, len(batch), 31)])) for p in zip(*(c.to_pylist() for c in out.columns))]
    want = set()
    for v in members:
        for a in members[v]:
            for b in members[v]:
                both = len(np.intersect1d(sets[a], sets[b]))
                if a < b and a // 8 != b // 8 and (hub[v, a] or hub[v, b]) and 100 * both >= 75 * (len(sets[a]) + len(sets[b]) - both):
                    want.add((a, b))
    assert set(got) == want and len(want) > 20


def test_a_hub_and_member_travels_in_one_row(spark, monkeypatch):
    """In a list of one chunk every member that is a hub is one row; in chunks a hub has one row for each. No pair is lost."""
    n, rows = 30, spark.sparkContext.accumulator(0)
    chosen = spark.createDataFrame([(7, d, 4, 4, 1.0, d, n, d % 3 > 0) for d in range(n)], "value bigint, doc_id bigint, n bigint, s bigint, share double, component bigint, members bigint, is_hub boolean")
    sketch = spark.createDataFrame([(d, [1, 2, 3, 4]) for d in range(n)], "doc_id bigint, sketch array<bigint>")
    meet = minhash._meet

    def counted(percent):
        def run(batches):
            def seen():
                for b in batches:
                    rows.add(b.num_rows)
                    yield b

            yield from meet(percent)(seen())

        return run

    monkeypatch.setattr(minhash, "_meet", counted)
    hubs = sum(d % 3 > 0 for d in range(n))
    for chunk, sent in ((1024, n), (10, 3 * hubs + n - hubs)):
        monkeypatch.setattr(minhash, "CHUNK", chunk)
        before = rows.value
        got = {tuple(r) for r in minhash.list_pairs(chosen, sketch, 75).collect()}
        assert got == {(a, b) for a in range(n) for b in range(a + 1, n) if a % 3 or b % 3}
        assert rows.value - before == sent
