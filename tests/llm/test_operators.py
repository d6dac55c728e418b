"""The training-data operators against brute-force versions and on edge cases."""

import hashlib
import json
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from predradius.llm import chat, decontaminate, exact_dedup, language_id, licenses, near_dedup, packing, queries, token_counts, toxicity, warc

DOC = "doc_id long, text string, lang string, source string, n_chars long, keep_id int, digest string"
LONG = "alpha beta gamma delta epsilon zeta eta theta iota kappa " * 3000


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, ties, repeats, a very long text and columns with clashing names."""
    texts = [None, "", "   \n\t", "one two", "ONE TWO", "one two", LONG, LONG, "ünï cödé ÜNÏ", "a</s>b [INST] <|end|>", "x" * 50_000]
    made = [(i if i != 3 else None, t, None, "s", 0, 1, "d") for i, t in enumerate(texts)]
    return spark.createDataFrame([*made, made[-2]], DOC)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def test_exact_dedup(odd, none):
    got = {r["doc_id"]: r for r in exact_dedup.exact_duplicates(odd).collect()}
    assert got[4]["keep_id"] == 5 and got[4]["group_size"] == 3 and got[6]["keep_id"] == 7 and got[0]["keep_id"] == 1
    assert got[5]["text_sha256"] == hashlib.sha256(b"one two").hexdigest()
    assert got[9]["group_size"] == 2 and got[9]["kept"]
    kept = exact_dedup.drop_exact_duplicates(odd)
    assert kept.columns == odd.columns and sorted(r[0] for r in kept.filter("doc_id is not null").collect()) == [1, 2, 5, 7, 8, 9, 10]
    assert exact_dedup.exact_duplicates(none).count() == 0


def test_exact_dedup_of_a_hot_text_with_clashing_columns(spark):
    made = [(i if i % 7 else None, "Hot" if i % 3 else f"t{i}", "x", i) for i in range(400)]
    docs = spark.createDataFrame(made + made[:50], "doc_id long, text string, own_0 string, kept long")
    want = {}
    for i, t, *_ in made:
        want.setdefault(t.lower(), []).append(i)
    got = {(r["doc_id"], r["text_sha256"]): (r["keep_id"], r["group_size"]) for r in exact_dedup.exact_duplicates(docs, runs=64).collect()}
    copies = defaultdict(int)
    for i, t, *_ in made + made[:50]:
        copies[t.lower()] += 1
    for t, ids in want.items():
        keep = max((i for i in ids if i is not None), default=None)
        assert all(got[i, hashlib.sha256(t.encode()).hexdigest()] == (keep, copies[t]) for i in ids)
    kept = exact_dedup.drop_exact_duplicates(docs)
    assert kept.columns == docs.columns and sorted(r["text"].lower() for r in kept.select("text").collect()) == sorted(want)


def test_exact_dedup_runs_agree(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    a, b = (sorted(map(tuple, exact_dedup.exact_duplicates(docs, runs=r, fan_in=f).collect())) for r, f in ((64, 8), (9, 2)))
    assert a == b


def brute_components(docs, percent=85):
    sets = {}
    for i, text in docs:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(text))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    label = {i: i for i in sets}
    ids = sorted(i for i in sets if sets[i])
    changed = True
    links = [(a, b) for x, a in enumerate(ids) for b in ids[x + 1 :] if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    while changed:
        changed = False
        for a, b in links:
            least = min(label[a], label[b])
            changed |= label[a] != least or label[b] != least
            label[a] = label[b] = least
    return {i: (len(sets[i]), label[i]) for i in sets}


def test_near_dedup(spark, sf_dir, odd, none):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    base = "w1 w2 w3 w4 w5 w6 w7 w8 w9 w10 w11 w12 w13 w14 w15 w16 w17 w18 w19 w20 ".split() + [f"v{i}" for i in range(180)]
    chain = []
    for step in range(6):  # each text close to the next, the ends far apart
        words = list(base)
        words[: 9 * step] = [f"z{i}" for i in range(9 * step)]
        chain.append((10_000 + step, " ".join(words)))
    docs = docs.union(spark.createDataFrame(chain, docs.schema))
    want = brute_components([tuple(r) for r in docs.collect()])
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicate_groups(docs).collect()}
    assert got == want and len({got[i][1] for i, _ in chain}) == 1
    assert near_dedup.near_duplicate_groups(none).count() == 0
    small = {r["doc_id"]: r["component_id"] for r in near_dedup.near_duplicate_groups(odd).filter("doc_id is not null").collect()}
    assert small[5] == 4 and small[7] == 6 and small[0] == 0 and small[1] == 1


def edited_copies(n, edits, vocabulary, seed):
    """n copies of one 400-word text, each with a few words of its own."""
    draw = np.random.default_rng(seed)
    out = []
    for i in range(n):
        words = [f"b{k}" for k in range(400)]
        for at in draw.choice(400, int(draw.choice(edits)), replace=False):
            words[at] = f"e{draw.integers(vocabulary)}"
        out.append((1000 + i, " ".join(words)))
    return out


@pytest.mark.parametrize("n, edits, vocabulary", [(150, [6], 1 << 30), (150, [3, 5, 7, 9, 12], 3), (120, [1, 2, 4, 8, 20], 200)])
def test_near_dedup_of_many_edited_copies(spark, monkeypatch, n, edits, vocabulary):
    """Copies that mostly link with no other: every link is found, and the pairs looked at stay far below all pairs."""
    made, looked = edited_copies(n, edits, vocabulary, 5), []
    confirm = near_dedup.Linker.confirm
    monkeypatch.setattr(near_dedup.Linker, "confirm", lambda self, pairs: (confirm(self, pairs), looked.append(self.looked_at.count())))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicate_groups(spark.createDataFrame(made, "doc_id long, text string")).collect()}
    assert got == brute_components(made)
    if vocabulary > 1000:
        assert looked[-1] < n * (n - 1) / 2 / 4


def test_near_dedup_of_an_id_with_several_texts(spark):
    a, b = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60))
    docs = spark.createDataFrame([(1, a), (1, b), (2, a + " end"), (3, b), (None, a), (4, None), (4, "")], "doc_id long, text string")
    got = sorted((str(r["doc_id"]), r["component_id"]) for r in near_dedup.near_duplicate_groups(docs).collect())
    assert got == [("1", 1), ("1", 1), ("2", 1), ("3", 1), ("4", 4), ("4", 4), ("None", 1)]
    assert sorted(r[0] for r in near_dedup.drop_near_duplicates(docs).filter("doc_id is not null").collect()) == [1, 1, 4, 4]


def test_registers_merge_and_estimate():
    own = near_dedup.Sketcher(30, 7)
    draw = np.random.default_rng(3)
    pool = draw.integers(0, 1 << 63, 3000).astype(np.uint64)
    a, b = pool[:2000], pool[500:2600]
    assert (near_dedup.merge_registers([own.registers(a), own.registers(b)]) == own.registers(pool[:2600])).all()
    found = near_dedup.joint_similarity(own.registers(a)[None], own.registers(b)[None], np.array([2000.0]), np.array([2100.0]))[0]
    assert abs(found - 1500 / 2600) < 0.12


def test_packing(spark, sf_dir, odd, none):
    from tokenizers import Tokenizer

    import public_tokenizers

    tok = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(60).select("doc_id", "text").union(odd.filter("doc_id is not null").select(F.col("doc_id") + 1000, "text").distinct())
    docs = docs.union(spark.createDataFrame([(5000, "hello <|endoftext|> x"), (5001, "<|endoftext|><|endoftext|>a<|endoftext"), (5002, "  <|endoftext|>\n")], docs.schema))
    pieces = packing.pack_documents(docs).collect()
    ids = {r["doc_id"]: [*tok.encode(r["text"] or "", add_special_tokens=False).ids, 1] for r in docs.collect()}
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for p in pieces:
        by_doc[p["doc_id"]].append(p)
        by_seq[p["sequence_id"]].append(p)
        part = np.array(ids[p["doc_id"]][p["start"] : p["start"] + p["length"]], "<u4")
        assert p["ids_crc32"] == zlib.crc32(part.tobytes()) and p["doc_tokens"] == len(ids[p["doc_id"]])
    for i, own in by_doc.items():
        at = 0
        for p in sorted(own, key=lambda p: p["start"]):
            assert p["start"] == at
            at += p["length"]
        assert at == len(ids[i])
    assert set(by_doc) == set(ids)
    for own in by_seq.values():
        at = 0
        for p in sorted(own, key=lambda p: p["offset"]):
            assert p["offset"] == at
            at += p["length"]
        assert at <= 2048
    assert packing.pack_documents(none).count() == 0


def test_differencing_is_even():
    draw = np.random.default_rng(1)
    sizes = draw.integers(20, 257, 900).tolist()
    made = packing.windows(sizes, 2048)
    sums = [sum(sizes[i] for i in w) for w in made]
    assert sorted(i for w in made for i in w) == list(range(900)) and max(sums) <= 2048 and max(sums) - min(sums) < 60


def test_token_counts(spark, sf_dir, odd, none):
    from predradius.llm.tokens import encoder

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text").union(odd.filter("doc_id is not null").select(F.col("doc_id") + 1000, "text").distinct())
    want = {r["doc_id"]: len(encoder().encode(r["text"])) for r in docs.collect()}
    for size in (7, 1000, 1 << 16):
        got = token_counts.document_token_counts(docs.repartition(3, "doc_id"), block_tokens=size).collect()
        assert {r["doc_id"]: r["n_tokens"] for r in got} == want and len(got) == len(want)
    assert token_counts.document_token_counts(none).count() == 0


def test_stitch_across_runs_and_open_tail(spark):
    flat, sep = [5, 5, 9, 9, 7, 7, 7, 7, 7, 9, 1], 9
    for size in (1, 2, 3, 4):
        blocks = spark.createDataFrame([(0, b, np.array(flat[b * size : (b + 1) * size], "<u2").tobytes()) for b in range(-(-len(flat) // size))], "file_id long, block long, tokens binary")
        got = token_counts.stitch(token_counts.find_separators(blocks, sep), run_blocks=2).orderBy("block").collect()
        assert [n for r in got for n in r["lengths"]] == [2, 0, 5] and got[-1]["open_tokens"] == 1


def test_chat_trees(spark, none):
    nodes = [(1, 1, None, "user", "hi", 0.0), (1, 2, 1, "assistant", "bad", 0.1), (1, 3, 1, "assistant", "good</s>", 0.9), (1, 4, 3, "user", "<|end|>", 0.5), (2, 1, 7, None, None, 0.0), (None, 1, None, "user", "x", 0.0)]
    df = spark.createDataFrame(nodes, "conv_id long, node long, parent long, role string, text string, score double").na.fill("")
    paths = chat.root_to_leaf_paths(df)
    assert sorted((str(r["conv_id"]), tuple(r["path"])) for r in paths.collect()) == [("1", (1, 2)), ("1", (1, 3, 4)), ("2", (1,)), ("None", (1,))]
    made = {r["conv_id"]: r for r in chat.format_paths(df, chat.rank_branches(paths)).collect()}
    assert chat.parse_formatted(made[1]["formatted"]) == [("user", "hi"), ("assistant", "good</s>"), ("user", "<|end|>")]
    spans = [made[1]["formatted"][s["from"] : s["to"]] for s in made[1]["loss_spans"]]
    assert [chat.unescape(s) for s in spans] == ["good</s>"]
    assert chat.format_conversations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def test_paths_of_random_trees(spark):
    draw = np.random.default_rng(3)
    nodes = []
    for conv in range(12):
        for n in range(1, 60):
            up = None if n == 1 else int(draw.integers(max(1, n - 1 - 4 * (conv % 3)), n))
            nodes.append((conv, n, up, "user", f"t{n}", float(draw.integers(0, 9)), "x", 1))
    nodes += [(99, 1, 2, "user", "", 0.0, "x", 1), (99, 2, 1, "user", "", 0.0, "x", 1), (99, 3, 2, "user", "", 0.0, "x", 1)]  # a cycle and a leaf below it
    up, score = {(c, n): p for c, n, p, *_ in nodes}, {(c, n): s for c, n, _, _, _, s, *_ in nodes}
    inner, want = {(c, p) for (c, _), p in up.items()}, {}
    for c, n in up:
        if c != 99 and (c, n) not in inner:
            path = [n]
            while up[c, path[0]] is not None:
                path.insert(0, up[c, path[0]])
            want[c, n] = (path, sum(score[c, x] for x in path) / len(path))
    df = spark.createDataFrame(nodes, "conv_id long, node long, parent long, role string, text string, score double, leaf string, i int")
    paths = chat.root_to_leaf_paths(df)
    assert {(r["conv_id"], r["leaf"]): (r["path"], r["score"]) for r in paths.collect()} == want
    best = {}
    for (c, n), (path, mean) in want.items():
        best[c] = min(best.get(c, ((1, 0, 0), None)), ((-mean, -len(path), n), path))
    made = chat.format_paths(df, chat.rank_branches(paths)).collect()
    assert {r["conv_id"]: [t for _, t in chat.parse_formatted(r["formatted"])] for r in made} == {c: [f"t{n}" for n in path] for c, (_, path) in best.items()}


def test_long_conversation(spark):
    turns = spark.range(20_000).selectExpr("7L AS conv_id", "id AS turn", "if(id % 2 = 0, 'user', 'assistant') AS role", "concat('w', id) AS text", "id AS node", "'x' AS branch")
    trees = chat.Trees(chat.linear_trees(turns))
    steps = trees.steps(trees.leaves())
    assert steps.count() == 20_000 and len(trees.jumps) <= 17 and trees.state.count() == 20_000
    got = chat.read_back(chat.format_conversations(turns)).first()
    want = "".join(f"{('user', 'assistant')[i % 2]}\nw{i}\n" for i in range(20_000))
    assert got["n_turns"] == 20_000 and got["turns_sha256"] == hashlib.sha256(want.encode()).hexdigest()


def test_roles_with_line_breaks(spark):
    made = [(1, 0, "us\ner", "a"), (1, 1, "assist\\nant", "b"), (1, 2, "</s>\\", "c\n")]
    got = chat.format_conversations(spark.createDataFrame(made, "conv_id long, turn long, role string, text string")).first()
    assert chat.parse_formatted(got["formatted"]) == [(r, t) for _, _, r, t in made]


@pytest.mark.parametrize("text", ["", "<|turn|>", "<\\|x", "</s></s>[INST]", "[\\\\INST]<s", "<<SYS>></SYS>", "<\\\\/s>\\"])
def test_escape_round_trip(spark, text):
    made = spark.createDataFrame([(text,)], "t string").select(chat.escape(F.col("t"))).first()[0]
    assert chat.unescape(made) == text and not any(c in made for c in ("<|", "</s>", "[INST]", "<s>"))


def test_language_id(spark, odd, none):
    d = "/root/testdata/sf0.01"
    got = queries.op8_language_id(spark, d).join(spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "lang"), "doc_id").filter("held_out")
    assert got.filter("lang = lang_pred").count() / got.count() > 0.97
    model = language_id.LanguageModel(["en"], np.zeros((1 << 16, 1), np.float32), np.zeros(1), 3, 16)
    out = {r["doc_id"]: r["lang_pred"] for r in model.transform(odd).collect()}
    assert out[0] == out[1] == out[2] == "und" and out[4] == "en"
    assert language_id.LanguageModel.fit(none.select("doc_id", "text", "lang")).predict("abc") == ("und", 0.0)


def test_language_matrix_equals_text_by_text(monkeypatch, spark):
    """Sparse matrices of few entries, so that texts are spread over several, against one sum for each text."""
    monkeypatch.setattr(language_id, "SLICE", 50)
    draw = np.random.default_rng(5)
    model = language_id.LanguageModel(["a", "b", "c"], draw.normal(size=(1 << 10, 3)).astype(np.float32), np.log([0.2, 0.3, 0.5]), 4, 10)
    texts = ["", None, "12 !", "x", "Ünï cödé", "the cat sat on the mat " * 9, "x", "a" * 333]
    langs, scores = model.predict_batch(texts)
    for text, lang, score in zip(texts, langs, scores, strict=True):
        points = language_id.folded(text)
        if points is None:
            assert (lang, score) == ("und", 0.0)
            continue
        total = model.priors + sum(model.weights[b].astype(float).sum(axis=0) for b in language_id.gram_buckets(points, 4, 10))
        assert lang == model.langs[int(total.argmax())] and np.isclose(score, 1 / np.exp(total - total.max()).sum())
    clash = spark.createDataFrame([(1, "abc", "q", 0.5), (1, "abc", "q", 0.5)], "doc_id long, text string, lang_pred string, score double")
    assert model.transform(clash).count() == 2 and model.transform(clash.limit(0)).count() == 0


def test_toxicity(spark, none):
    d = "/root/testdata/sf0.1"
    got = queries.op4_toxicity(spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").filter("held_out").toPandas()
    toxic, clean = got[got["toxic"] == 1], got[got["toxic"] == 0]
    assert toxic["predicted"].mean() > 0.8 and clean["predicted"].mean() < 0.02
    model = toxicity.ToxicityModel.fit(none.select("text", F.lit(1).alias("toxic")))
    assert model.score("you 1d10t") > 0.3 > model.score(None)
    assert toxicity.Lexicon({"trash": 5.0}).matches("the trash can is trash!")[0] == [5.0]


def test_warc(spark):
    pages = spark.createDataFrame([(1, "http://a/b", "<html><head><title>T &amp; U</title></head><body><p>x</p><script>no</script><a href='/l'>y</a></body></html>"), (2, None, None)], "page_id long, url string, html string")
    sources = warc.responses(pages)
    made = warc.build_derivatives(sources).collect()
    assert sorted(made, key=lambda r: r["record_id"]) == sorted(warc.page_derivatives(pages).collect(), key=lambda r: r["record_id"])
    ids = {r["page_id"]: r["record_id"] for r in sources.collect()}
    assert len(made) == 4 and all(r["refers_to"] == ids[r["page_id"]] and f"WARC-Refers-To: {ids[r['page_id']]}" in r["headers"] for r in made)
    text = next(r["block"] for r in made if (r["page_id"], r["kind"]) == (1, "conversion"))
    meta = json.loads(next(r["block"] for r in made if (r["page_id"], r["kind"]) == (1, "metadata")))
    assert text == "x\ny" and meta["html"] == {"title": "T & U", "links": ["/l"]}


def test_warc_headers_and_open_markup(spark):
    bad = "<script>" * 3000 + "<!--" * 3000 + "<a " * 3000 + "<title"
    pages = spark.createDataFrame([(1, "http://a\r\nWARC-Date: x", "<p>a</p>", 1), (1, "http://a\r\nWARC-Date: x", "<p>a</p>", 1), (2, "u", bad, 2), (3, "v", "<a name=n><a x href='q>r'>t</a><a href=z>", 3)], "page_id long, url string, html string, kind int")
    made = warc.page_derivatives(pages).collect()
    fields = [warc.header_fields(r["headers"]) for r in made]
    assert len(made) == 8 and all(f["WARC-Date"] == "2020-01-01T00:00:00Z" for f in fields)
    assert json.loads(next(r["block"] for r in made if (r["page_id"], r["kind"]) == (3, "metadata")))["html"]["links"] == ["q>r", "z"]
    assert warc.page_derivatives(pages.filter("page_id > 9")).count() == 0


def brute_lexicon(weights, exceptions, text):
    """The heaviest entry at each word that no exception phrase covers, by trying every entry at every place."""
    spaced, found = " " + text, {}
    covered = {i for x in exceptions for i in range(len(spaced)) if spaced.startswith(" " + x, i) and not spaced[i + 1 + len(x) : i + 2 + len(x)].isalpha() for i in range(i + 1, i + 1 + len(x))}
    for i in range(1, len(spaced)):
        if spaced[i - 1].isalpha() or not spaced[i].isalpha() or i in covered:
            continue
        word = re.match(r"[^\W\d_]+", spaced[i:])[0]
        best = max([w for e, w in weights.items() if e == word or e.endswith("*") and word.startswith(e[:-1])], default=0)
        if best:
            found[i] = best
    return sorted(found.values())


def test_toxicity_matcher_equals_brute_force():
    weights, exceptions = {"trash": 3.0, "tra*": 1.0, "idiot": 5.0, "idi*": 2.0, "can": 1.5}, ("trash can", "idiot proof")
    draw, words = np.random.default_rng(4), ["trash", "can", "idiot", "proof", "tram", "canister", "idiom", "x", "9", "proofs"]
    lexicon = toxicity.Lexicon(weights, exceptions)
    for _ in range(300):
        text = "".join(w + s for w, s in zip(draw.choice(words, 12), draw.choice([" ", " ", ", ", "-"], 12), strict=True))
        assert sorted(lexicon.matches(text)[0]) == brute_lexicon(weights, exceptions, text), text
    for text in ("1d107", "ＩＤＩＯＴ", "idio7", "ídíót"):
        assert lexicon.matches(text)[0] == [5.0]


def test_decontamination(spark, sf_dir, odd, none):
    bench = spark.createDataFrame([(1, "A train leaves at 9 and travels 120 km in 2 hours before it stops at the old stone bridge near town"), (2, "tiny item here"), (3, None)], "item_id long, text string")
    docs = spark.createDataFrame([(1, "Noise first. A train leaves at 9 and travels 120 km in 2 hours before it stops at the old stone bridge near town. More."),
                                  (2, "A train leaves at 7 and travels 300 km in 5 hours before it stops at the old stone bridge near town"), (3, "nothing of the kind is to be found in this text at all, not one window"), (4, "so a tiny item here too")], "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["kind"] for r in decontaminate.leaks(docs, bench).collect()}
    assert got == {(1, 1): "verbatim", (2, 1): "reparameterised", (4, 2): "verbatim"}
    assert decontaminate.leaks(odd, bench).count() == 0 and decontaminate.leaks(none, bench).count() == 0
    assert decontaminate.leaks(docs, bench.filter("item_id > 9")).count() == 0
    assert decontaminate.drop_leaks(docs, bench).select("doc_id").collect()[0][0] == 3


def test_decontamination_checks_every_placement(spark):
    series = "write the numbers 3 1 4 15 9 2 6 5 35 8 in a row and then read them back to the class aloud please"
    shop = "the shop sold {} red apples and {} green pears to its guests and "
    item = shop.format(12, 7) + shop.format(15, 9) + "then it closed"
    bench = spark.createDataFrame([(1, series), (2, item)], "item_id long, text string")
    docs = spark.createDataFrame([
        (1, series), (2, item), (3, shop.format(99, 98) + "so on. " + item), (4, shop.format(1, 2) + shop.format(3, 4) + "then it closed"),
        (5, "the shop sold 8 red apples and 6 green pears to its very kind guests and the shop sold 5 red apples and 4 green pears to its guests and then it closed"),
        (6, series.replace("15 9 2", "15 9 2 77"))], "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r for r in decontaminate.leaks(docs, bench).collect()}
    want = {(1, 1): "verbatim", (2, 2): "verbatim", (3, 2): "verbatim", (4, 2): "reparameterised", (5, 2): "reparameterised"}
    assert {k: got[k]["kind"] for k in want} == want
    assert got[1, 1]["coverage"] == got[2, 2]["coverage"] == got[3, 2]["coverage"] == got[4, 2]["coverage"] == 1
    torn = spark.createDataFrame([(1, "a man paid 5 coins and his friend also paid 6 coins to the old man")], "doc_id long, text string")
    same = spark.createDataFrame([(1, "a man paid 9 coins and his friend also paid 9 coins to the old man")], "item_id long, text string")
    assert decontaminate.leaks(torn, same).count() == 0


def test_decontamination_reads_names_at_sentence_starts(spark):
    asked = "{0} earns {1} dollars an hour. Yesterday, {0} did 50 minutes of work. {0} paid 3 dollars. How much did {0} keep?"
    bench = spark.createDataFrame([(1, asked.format("Weng", 12))], "item_id long, text string")
    docs = spark.createDataFrame([(1, asked.format("Maria", 15)), (2, "Noise here.\n\"" + asked.format("Maria", 15) + "\" More noise."), (3, asked.format("Weng", 12)),
                                  (4, "Olga earns 12 dollars an hour. Yesterday, Petra did 50 minutes of work. Maria paid 3 dollars. How much did Nina keep?")], "doc_id long, text string")
    assert {r["doc_id"]: (r["kind"], r["coverage"]) for r in decontaminate.leaks(docs, bench).collect()} == {1: ("reparameterised", 1.0), 2: ("reparameterised", 1.0), 3: ("verbatim", 1.0)}


def test_decontamination_finds_every_passage(spark):
    d = "/root/testdata/sf0.01"
    docs, bench = ([tuple(r) for r in spark.read.parquet(f"{d}/{t}.parquet").select(k, "text").collect()] for t, k in (("documents", "doc_id"), ("benchmark", "item_id")))
    want = {(i, j) for i, t in docs for j, b in bench if b.lower() in t.lower()}
    assert {(r["doc_id"], r["item_id"]) for r in queries.op10_decontamination(spark, d).collect()} >= want


def test_licenses(spark, odd, none):
    notice = licenses.TEMPLATES["GPL header"].upper()
    docs = spark.createDataFrame([(1, "word " * 90 + notice + " word" * 40), (2, "some words Released under the MIT License."), (3, "released the licence of words")], "doc_id long, text string")
    got = {(r["doc_id"], r["template"]) for r in licenses.notices(docs).collect()}
    assert got == {(1, "GPL header"), (2, "MIT short")}
    assert licenses.notices(odd).count() == 0 and licenses.notices(none).count() == 0


def test_licenses_short_templates(spark):
    docs = spark.createDataFrame([(1, "word " * 90 + "end.\nAll rights reserved."), (2, "ALL RIGHTS RESERVED"), (3, "all the rights are reserved"), (4, "x " * 7 + "all rights reserved " + "y " * 7), (5, "Copyleft")], "doc_id long, text string")
    assert {(r["doc_id"], r["template"]) for r in licenses.notices(docs).collect()} == {(1, "All rights short"), (2, "All rights short"), (4, "All rights short")}
    own = {"a": "All rights reserved", "b": "copyleft", "c": "word word word word word"}
    assert {(r["doc_id"], r["template"]) for r in licenses.notices(docs, own).collect()} == {(1, "a"), (1, "c"), (2, "a"), (4, "a"), (5, "b")}
    with pytest.raises(ValueError):
        licenses.notices(docs, {"none": "..."})


def test_pipeline_drops_near_copies_from_080(spark, sf_dir):
    import corpus_pipeline

    made = []
    for i in range(20):  # pairs at 176 of 216 shingles, 0.815, and at 166 of 226, 0.735
        words = [f"w{i}x{k}" for k in range(200)]
        for j, n in ((100, 20), (200, 30)):
            own = [f"{w}y{j}" for w in words]
            made += [(j + i, " ".join(own)), (1000 + j + i, " ".join([f"z{i}x{k}y{j}" for k in range(n)] + own[n:]))]
    docs = spark.createDataFrame(made, "doc_id long, text string")
    kept = {r["doc_id"] for r in corpus_pipeline.near_dedup_stage(spark, docs, sf_dir).collect()}
    assert kept == {i for i, _ in made if not 1100 <= i < 1200}
