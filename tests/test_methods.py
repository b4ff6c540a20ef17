"""Methods against plain versions, invariants and the planted classes of the fixtures."""

import gzip
import types

import numpy as np
import pytest
from pyspark.sql import functions as F

from corpusmill.functions import choice, formula
from corpusmill.functions import code as code_functions
from corpusmill.functions import html as H
from corpusmill.functions import text as T
from corpusmill.operators import extract, joins, keywords, measures, minhash, models, paragraphs, rules
from corpusmill.plans import fixtures, methods, relational, tracks
from corpusmill.session import scratch
from corpusmill.sources import warc
from corpusmill.streaming.queries import BandIndex, queries, stream_incremental_lsh

SF = "/root/testdata/sf0.001"


def test_modular_arithmetic_is_exact():
    rng = np.random.default_rng(0)
    a, h, b = (rng.integers(0, 2**n, 2000, dtype=np.uint64) for n in (61, 60, 60))
    got = minhash._times(a, h, b)
    assert all(int(g) == (int(x) * int(y) + int(z)) % minhash.PRIME for g, x, y, z in zip(got, a, h, b, strict=True))


def test_collision_rate_follows_the_curve():
    rng = np.random.default_rng(1)
    a, b = minhash.constants(117)
    for level, want in ((0.5, 0.0011), (0.7, 0.084), (0.8, 0.399), (0.9, 0.929)):
        hit = 0
        for _ in range(150):
            both = int(200 * level)
            own = (200 - both) // 2
            h = rng.integers(0, 2**60, both + 2 * own, dtype=np.uint64)
            sig = [minhash._times(a[:, None], x[None, :], b[:, None]).min(axis=1) for x in (h[: both + own], np.r_[h[:both], h[both + own :]])]
            hit += any((sig[0][k : k + 13] == sig[1][k : k + 13]).all() for k in range(0, 117, 13))
        assert abs(hit / 150 - want) < 0.13


def test_survivors_of_graph_and_bucket(spark):
    bands = methods._bands(spark, SF)
    bucket = {r.doc_id for r in minhash.dedup_lsh(bands).collect()}
    graph = {r.doc_id for r in minhash.dedup_components(minhash.candidate_pairs(bands)).where("doc_id <> component").collect()}
    assert bucket <= graph


def test_incremental_equals_one_pass(spark):
    one = {(r.doc_id, r.witness) for r in minhash.dedup_lsh(methods._bands(spark, SF)).collect()}
    assert {(r.doc_id, r.witness) for r in stream_incremental_lsh(spark, SF).collect()} == one


def test_paragraph_removal_grows_with_scope_and_is_idempotent(spark, tables):
    docs = tables("documents").withColumn("snapshot", paragraphs.snapshot(F.col("source")))
    sums = [paragraphs.dedup_paragraphs(docs, scope=s).agg(F.sum("n_removed")).first()[0] for s in (("snapshot", "source"), ("snapshot",), ())]
    assert sums == sorted(sums)
    once = paragraphs.dedup_paragraphs(docs).select("doc_id", F.col("text_dedup").alias("text"))
    assert paragraphs.dedup_paragraphs(once).agg(F.sum("n_removed")).first()[0] == 0


def test_thresholds_at_equality(spark):
    # Fifty words pass, forty-nine fail; a mean of exactly three characters passes.
    rows = [(0, "of the " + "abc " * 47), (1, "of the " + "abc " * 48), (2, "abc def"), (3, ""), (4, None)]
    got = {r.doc_id: r for r in rules.score_document_rules(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[0].f_words and not got[1].f_words and not got[2].f_mean_word and got[3].f_words and not got[3].f_mean_word


def test_sentence_rules():
    hit = lambda s: [n for n, h in zip(rules.SENTENCE_RULES, rules.sentence_hits(s), strict=True) if h]
    assert hit("3 likes") == ["counter"] and hit("1,234") == ["numeric", "one_word"] and hit("sign-in to go on now") == ["sign_in"]
    assert hit("you may read more...") == ["read_more"] and hit("two items in card") == ["items_in_card"] and hit("hello there") == []
    assert hit("ABCDEF ghij klm") == [] and "upper" in hit("ABCDEFG hi")


def test_coverage_against_character_marks():
    words = "a bb c d e f a bb c d e g a bb c d e".split()
    _, _, cover = rules.ngram_counts(words, rules.DUP_NGRAM, rules.TOP_NGRAM)
    assert cover[5] == sum(map(len, words)) - 2 and cover[6] == 0


def test_latex_checks():
    good = [r"\frac{a}{b}", r"\frac12", r"\sqrt[3]{x}", r"x_{i}^{2}", r"\left( x \right)", r"\begin{cases} a & b \\ c & d \end{cases}", r"\alpha + \beta", r"a \text{ if } b", r"\{ x \}", "f'(x) = 0"]
    bad = [r"\frac{a}", "{x", "x}", "x^", r"\left( x", r"\begin{matrix} a \end{cases}", "a & b", "x_^2", "", "\\"]
    assert all(formula.check_latex(x)[0] for x in good) and not any(formula.check_latex(x)[0] for x in bad)


def test_code_families():
    assert not any(code_functions.looks_like_code("two plain words").values())
    for text in ("def f(x):", "x = 5", "print(x)", "a -> b", "const y = 3;"):
        assert any(code_functions.looks_like_code(text).values()), text


def test_planted_code(spark):
    got = {r.page_id: r for r in tracks.code_track().run(fixtures.derived(spark, SF, fixtures.code_sql())).df.collect()}
    pages = [r.page_id for r in spark.read.parquet(f"{SF}/pages.parquet").collect()]
    for p in pages:
        m, blocked = p % 12, p % 48 in (0, 12)
        want = m in (0, 1, 3, 6, 8, 9, 10) and not blocked
        assert (p in got) == want, (p, m)
        if want:
            assert got[p].n_snippets == 1
            if m == 6:
                assert got[p].snippets == ["shown = f(2)"]
            if m == 8:
                assert got[p].snippets == ["a = f(1)\nb = f(2)\nc = f(3)\nd = f(4)"]
            if m == 9:
                assert "77" in got[p].snippets[0] and "10" not in got[p].snippets[0]


def test_planted_formulas(spark):
    pages = fixtures.derived(spark, SF, fixtures.math_sql())
    got = {r.page_id: r for r in extract.math_pass(keywords.keep_math_page(pages)).collect()}
    for r in pages.select("page_id").collect():
        m = r.page_id % 12
        if m == 11:
            assert r.page_id not in got
        else:
            assert (got[r.page_id].n_formulas, got[r.page_id].keep) == ((0, False) if m in (8, 10) else (1, m not in (2, 9))), m
    assert "\\[" in next(x.text for k, x in got.items() if k % 12 == 1) and "\\(" in got[0].text


def test_raw_tables_pass_nothing(spark, tables):
    assert tracks.code_track().run(tables("pages")).df.count() == 0
    assert tracks.math_markup_track().run(tables("pages")).df.count() == 0
    assert tracks.open_qa_track().run(tables("documents").select("doc_id", "text")).df.count() == 0


def test_choice_questions():
    text = "lead\n12. What is it?\na) red\nb) green\nc) blue\nanswer: b\nexplanation: because"
    [q] = choice.choice_questions(text)
    assert choice.format_question(q) == "What is it?\nA. red\nB. green\nC. blue\nAnswer: b\nExplanation: because"
    assert choice.choice_questions("stem\na. x\nc. y\nanswer: a") == [] and choice.choice_questions("stem\nA - x\nB - y") == []
    before = "answer: a\nstem\na> x\nb> y"
    assert choice.choice_questions(before) == [] and len(choice.choice_questions(before, "any")) == 1
    # i, c and d are letters and roman numerals: the run decides.
    assert choice.choice_questions("stem\ni. x\nii. y\niii. z\nans: i")[0].style == "roman"


def test_choice_runs_go_on_past_ten():
    romans = "i ii iii iv v vi vii viii ix x xi xii xiii xiv xv".split()
    for style, marks in (("letter", [chr(97 + k) for k in range(26)]), ("arabic", [str(k) for k in range(1, 131)]), ("roman", romans), ("letter", list("abcdefghijkl"))):
        for answer in ("after", "before"):
            options = [f"{m}) opt {m}" for m in marks]
            lines = ["stem", *options, "answer: b"] if answer == "after" else ["answer: b", "stem", *options]
            [q] = choice.choice_questions("\n".join(lines), answer)
            assert (q.style, len(q.options), q.answer) == (style, len(marks), "answer: b")
            assert len(choice.format_question(q).split("\n")) == len(marks) + 2
    assert choice.roman("iiii") is None and choice.roman("xlix") == 49 and choice._letters(27) == "AB"


def test_question_marker_alone_passes_both_sides(spark):
    df = spark.createDataFrame([(1, "Q&A"), (2, "data: x what"), (3, "what is")], "doc_id long, text string")
    got = {r.doc_id: (r.keep, r.keep_bounded) for r in keywords.score_qa_keywords(df).collect()}
    assert got == {1: (True, True), 2: (True, False), 3: (False, False)}


def test_main_content_of_given_pages(tables):
    for r in tables("pages").collect():
        text = H.main_content(r.html)
        nav = r.html.partition("<footer")[2].partition("</footer>")[0]
        words = [w for w in T.py_words(H.parse(nav).text()) if len(w) > 12]
        assert text and not any(line in text for line in words if line not in r.html.partition("<article")[2].partition("</article>")[0])
    assert H.main_content("<p><b>un<p>closed") is not None and H.linearize(H.parse("<ul><li>a<li>b</ul>x&amp;y")) == "a\nb\nx&y"


def test_any_broken_html_gives_a_tree():
    for cut in range(0, 400, 7):
        H.linearize(H.parse(("<html><!DOCTYPE x><script>var t='</p>'</script><table><tr><td a=b>x</tr><![CDATA[" * 5)[:cut]))


def test_language_and_quality_models(spark, tables):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = models.train_language_model(docs.where(~models.held_out()))
    got = models.score_language(docs.where(models.held_out() & (F.col("n_chars") >= 100)), model).agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0]
    assert got >= 0.95
    assert models.language_of("", model) == ("und", 0.0)


def test_language_is_told_from_whole_texts(spark, monkeypatch):
    rng = np.random.default_rng(3)
    word = lambda letters: "".join(rng.choice(list(letters), 5))
    texts = {k: " ".join(word(a) for _ in range(3000)) for k, a in (("aa", "abcdefgh"), ("bb", "klmnopqr"))}
    wide = "".join(chr(0x4E00 + k) for k in range(20_902))  # more grams than the cut let through
    rows = [(1, "aa", texts["aa"]), (2, "bb", texts["bb"]), (3, "cc", wide), (4, None, texts["aa"][:2500] + " " + texts["bb"]), (5, None, texts["bb"][:2500] + " " + texts["aa"]), (6, None, "?"), (7, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    model = models.train_language_model(df)
    got = {r.doc_id: (r.lang_pred, r.lang_prob) for r in models.score_language(df, model).collect()}
    assert [got[k][0] for k in range(1, 8)] == ["aa", "bb", "cc", "bb", "aa", "und", "und"]
    assert len(model["grams"]) >= 3 * 20_000
    monkeypatch.setattr(models, "BLOCK", 7)
    plain = lambda t: {t[i : i + n]: 0 for n in (1, 2, 3) for i in range(len(t) - n + 1)}
    g, n = models.gram_counts("Ab-- cd,1 ABAB ab. ")
    assert len(g) == len(plain("ab cd abab ab")) and n.sum() == 13 + 12 + 11
    monkeypatch.setattr(models, "BROADCAST_COUNTS", 10)
    joined = models.train_language_model(df)
    assert "table" in joined
    far = {r.doc_id: (r.lang_pred, r.lang_prob) for r in models.score_language(df, joined).collect()}
    assert all(far[k][0] == got[k][0] and abs(far[k][1] - got[k][1]) < 1e-9 for k in got)


def test_scorer_is_loaded_per_worker(spark, tables):
    class Length(models.Scorer):
        def load(self):
            self.ready = True

        def score(self, texts):
            assert self.ready
            return [float(len(t)) for t in texts]

    got = models.score_with(tables("documents").select("text"), Length()).where("p_quality <> length(text)").count()
    assert got == 0


def test_balanced_sample_ignores_partitioning(spark, tables):
    labels = tables("labels").select("doc_id", F.col("quality").alias("label"))
    pick = lambda d: sorted(map(tuple, models.balanced_sample(d, "label", 5).collect()))
    assert pick(labels) == pick(labels.repartition(7))


def test_perplexity_prefers_its_own_text(spark):
    a = spark.createDataFrame([("the cat sat on the mat " * 20,)], "text string")
    b = spark.createDataFrame([("x y z q r s " * 20,)], "text string")
    ppl = lambda t: measures.perplexity(measures.train_ngram_lm(t), a).first().perplexity
    assert ppl(a) < ppl(b)


def test_warc_source_round_trip(spark, tables, tmp_path):
    spark.dataSource.register(warc.WarcSource)
    pages = tables("pages").select("url", F.col("html").alias("payload"))
    out = str(tmp_path / "w")
    pages.repartition(2).write.format("warc").mode("append").save(out)
    want = sorted(map(tuple, pages.collect()))
    back = spark.read.format("warc").load(out)
    assert sorted((r.url, r.payload) for r in back.where("type = 'response' and error is null").collect()) == want
    binary = warc.read_binary(spark, out)
    assert sorted((r.url, r.payload) for r in binary.select("url", "payload").collect()) == want
    (tmp_path / "bad").mkdir()
    whole = warc.record_bytes("conversion", "http://x/", "text")
    (tmp_path / "bad" / "a.wet").write_bytes(whole + whole[:-6])
    (tmp_path / "bad" / "b.warc.gz").write_bytes(gzip.compress(whole)[:-9])
    (tmp_path / "bad" / "c.warc").write_bytes(b"WARC/1.0\r\nWARC-Type: response\r\n\r\n")
    (tmp_path / "bad" / "d.warc").write_bytes(warc.record_bytes("conversion", "http://y/", "").replace(b"Content-Length: 0", b"Content-Length: 2")[:-4] + b"\xff\xfe\r\n\r\n")
    rows = spark.read.format("warc").load(str(tmp_path / "bad")).collect()
    assert sorted(r.error for r in rows if r.error and not r.error.startswith("broken")) == ["cut off", "no length"] and any(r.url == "http://y/" for r in rows)


def test_plans_push_filters_and_keep_texts_out_of_shuffles(spark):
    plan = lambda df: df._jdf.queryExecution().toString()
    pages = spark.read.parquet(f"{SF}/pages.parquet")
    assert "StringContains" in plan(keywords.keep_code_page(pages)) and "StringContains" in plan(keywords.keep_math_page(pages))
    assert plan(tracks.code_track().run(pages).df).count("MapInPandas") >= 1
    dedup = plan(minhash.dedup_lsh(minhash.lsh_bands(minhash.minhash_signatures(spark.read.parquet(f"{SF}/documents.parquet"))))).partition("== Physical Plan ==")[2]
    assert "CartesianProduct" not in dedup and not any("Exchange" in line and "text" in line for line in dedup.splitlines())


def test_track_funnel_and_domain_template(spark, tables):
    spec = tracks.DomainSpec("medicine", ("the",), lambda d: d.withColumn("hits", F.lit(1)), lambda d: d.where("hits > 0"), column="text")
    rows = {r.step: r.docs for r in spec.track().run(tables("documents").select("doc_id", "text")).funnel().collect()}
    assert rows[0] >= rows[1] >= rows[3]


def test_whole_vector_search_takes_every_twentieth_row(spark, monkeypatch):
    monkeypatch.setattr(relational, "VEC_BLOCK", 64)
    got = relational.vec_cosine_topk(spark, SF).collect()
    ids = {r.vec_id for r in spark.read.parquet(f"{SF}/embeddings.parquet").select("vec_id").collect()}
    assert {r.probe for r in got} == {i for i in ids if i % 20 == 0} and len(got) == 5 * len({r.probe for r in got})
    v = {r.vec_id: np.array(r.embedding, float) for r in spark.read.parquet(f"{SF}/embeddings.parquet").collect()}
    cosine = lambda x, y: round(float(x @ y / np.sqrt((x @ x) * (y @ y))), 5)
    want = sorted((i for i in v if i), key=lambda i: (-cosine(v[0], v[i]), i))[:5]
    assert [r.vec_id for r in sorted((r for r in got if r.probe == 0), key=lambda r: r["rank"])] == want


def test_whole_mixture_uses_up_the_scarcer_source(spark):
    docs = methods._docs(spark, SF)
    all_ = {r[0]: r[1] for r in docs.groupBy(F.when(F.col("lang") == "en", "web").otherwise("code")).agg(F.sum(measures.token_count(F.col("text")))).collect()}
    got = {r.track: r.tokens for r in methods.mixture_web_code(spark, SF).collect()}
    unit = min(all_["web"] // 4, all_["code"])
    assert got["web"] >= 4 * unit and got["code"] >= unit
    assert got["web"] == all_["web"] or got["code"] == all_["code"]
    assert 0.78 < got["web"] / (got["web"] + got["code"]) < 0.9


def test_registered_tracks_run_their_models(spark):
    v = methods.web_warc_verdicts(spark, SF)
    keeps = ["keep_lang", "keep_repetition", "keep_rules", "keep_sentences", "keep_model", "keep_lsh"]
    kept = {r.doc_id for r in v.collect() if all(r[k] for k in keeps)}
    assert kept == {r.doc_id for r in methods.web_warc_corpus(spark, SF).collect()}
    assert {r.doc_id for r in methods.open_qa_corpus(spark, SF).collect()} < {r.doc_id for r in tracks.open_qa_track().run(methods._qa(spark, SF)).df.collect()}
    got = {r.recipe: r for r in methods.recipe_comparison_models(spark, SF).collect()}
    old = {r.recipe: r for r in methods.recipe_comparison(spark, SF).collect()}
    assert set(got) == set(methods._RECIPES) and all(got[k] == old[k] for k in old)
    assert 0 < got["full"].docs <= min(got["rules_only"].docs, got["model_only"].docs) < got["raw"].docs
    assert {r.recipe for r in methods.recipe_perplexity_models(spark, SF).collect()} == set(methods._RECIPES)


def test_auc_counts_ties_half(spark):
    rows = [(1, 0.9), (1, 0.5), (0, 0.5), (0, 0.1), (None, 0.7)]
    got = measures.auc(spark.createDataFrame(rows, "y int, s double"), "y", "s").first()
    assert (got.positives, got.negatives, got.auc) == (2, 2, 0.875)
    one_class = measures.auc(spark.createDataFrame(rows[:2], "y int, s double"), "y", "s").first()
    assert one_class.auc is None


def test_own_keyword_dictionary(spark, tmp_path):
    path = tmp_path / "words.txt"
    path.write_text("\\foo\n\nbar\nfoo\n")
    words = keywords.load_keywords(spark, str(path))
    assert words == ["bar", "foo"]
    df = spark.createDataFrame([(1, "\\foo \\bar \\frac")], "doc_id long, text string")
    assert keywords.score_math_keywords(df, commands=words).first().latex_hits == 2


def test_trees_of_any_depth():
    n = 3000
    deep = "<div>" * n + '<a href="x">far below</a> and a line of text outside the link.' + "</div>" * n
    root = H.parse(deep)
    assert H.links(root) == ["x"] and H.linearize(root) == "far below and a line of text outside the link."
    assert H.main_content(deep) == "far below and a line of text outside the link."
    assert H.strip_hidden(H.parse('<p style="display:none">' + "<b>" * n + "x")) == 1


def test_hidden_inside_hidden_counts_once_and_style_rules_are_an_option():
    page = "<style>.off, p#b { display : none }</style><p class='x off'>one<b aria-hidden='true'>two</b></p><p id='b'>three</p><p>four</p>"
    assert H.strip_hidden(H.parse(page)) == 3
    root = H.parse(page)
    assert H.strip_hidden(root, style_rules=True) == 11 and H.linearize(root) == "four"


def test_prefix_filter_loses_no_pair(spark):
    rng = np.random.default_rng(5)
    texts = [" ".join(rng.choice(list("abcd"), rng.integers(1, 9))) for _ in range(120)]
    sets = [set(minhash.shingles(t, 2)) for t in texts]
    docs = spark.createDataFrame([*enumerate(texts), (500, None), (501, "")], "doc_id long, text string")
    for tenths in (3, 5, 8, 10):
        got = {(r.a, r.b): (r.both, r.either) for r in minhash.jaccard_pairs(docs, tenths, 2).collect()}
        both = {(a, b): (len(sets[a] & sets[b]), len(sets[a] | sets[b])) for a in range(120) for b in range(a + 1, 120)}
        assert got == {k: v for k, v in both.items() if v[0] * 10 >= v[1] * tenths}


def test_a_batch_run_again_changes_no_index(spark, tmp_path):
    index = BandIndex(spark, str(tmp_path / "index"))
    rows = lambda *r: spark.createDataFrame([(i, 0, k) for i, k in r], "doc_id long, band int, key string")
    assert index.losers(rows((1, "k"), (2, "l"), (3, "l")), 0).collect() == [(3, 2)]
    for _ in range(2):
        assert sorted(index.losers(rows((4, "k"), (5, "m"), (6, "l")), 1).collect()) == [(4, 1), (6, 2)]
    assert sorted((r.key, r.first_id, r.batch) for r in spark.read.schema(index.SCHEMA).parquet(index.path).collect()) == [("k", 1, 0), ("l", 2, 0), ("m", 5, 1)]


def test_scratch_needs_a_shared_folder_on_a_cluster():
    def session(master, shared):
        context = types.SimpleNamespace(master=master, getCheckpointDir=lambda: None)
        return types.SimpleNamespace(sparkContext=context, conf=types.SimpleNamespace(get=lambda k, default: shared))

    assert scratch(session("spark://x", "/shared")) == "/shared" and scratch(session("local[2]", None))
    with pytest.raises(RuntimeError):
        scratch(session("spark://x", None))


def test_copies_cost_a_class_one_row(spark):
    one, two = "a b c d e f g h", "a b c d e f g i"
    docs = spark.createDataFrame([(i, one if i % 2 else two) for i in range(400)] + [(500, "x y z")], "doc_id long, text string")
    members, pairs = minhash.jaccard_classes(docs, 5, 2)
    assert [(r.a, r.b, r.na, r.nb, r.both) for r in pairs.collect()] in ([(0, 1, 7, 7, 6)], [(1, 0, 7, 7, 6)])
    assert sorted((r.rep, r["size"], r.doc_id % 2) for r in members.where("doc_id in (7, 8, 500)").collect()) == [(0, 200, 0), (1, 200, 1), (500, 1, 0)]
    got = minhash.jaccard_pairs(docs, 5, 2).groupBy("both", "either").count().collect()
    assert sorted(tuple(r) for r in got) == [(6, 8, 200 * 200), (7, 7, 2 * 199 * 100)]


def test_lsh_against_exact_lists_no_copies(spark, tmp_path, monkeypatch):
    monkeypatch.delattr(minhash, "candidate_pairs")
    text = " ".join(f"w{i}" for i in range(40))
    rows = [(i, text if i < 300 else text.replace("w39", "z"), "en", "s0", 300) for i in range(400)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    out = methods.lsh_vs_exact(spark, str(tmp_path))
    got = {r.tenths: (r.pairs, r.found) for r in out.collect()}
    assert got[10] == (300 * 299 // 2 + 100 * 99 // 2,) * 2 and got[9][0] == 300 * 100 and got[9][1] in (0, 30000)


def test_beaten_counts_make_no_pairs(spark):
    rng = np.random.default_rng(3)
    rows = [(i, "ab"[i % 2], float(rng.integers(0, 40)), int(rng.integers(0, 9))) for i in range(300)] + [(900, "a", None, 3), (901, None, 1.0, 3), (902, "a", 1.0, None)]
    df = spark.createDataFrame(rows, "id long, brand string, price double, size long")
    out = joins.beaten_counts(df, ["brand"], "price", "size", "n")
    got = {r.id: r.n for r in out.collect()}
    want = {a[0]: sum(b[1] == a[1] and b[2] < a[2] and b[3] > a[3] for b in rows[:300]) for a in rows[:300]}
    assert got == {k: v for k, v in want.items() if v}


def test_streams_leave_no_table_on_the_driver(spark):
    before = {t.name for t in spark.catalog.listTables()}
    assert queries()["stream_dedup"](spark, SF).count() and queries()["stream_session"](spark, SF).count()
    assert {t.name for t in spark.catalog.listTables()} == before


@pytest.mark.parametrize("key", ["code_snippet_tests", "compare_runs", "line_numbers_removed", "lsh_chain_fixture", "lsh_curve", "macro_average"])
def test_key_reads_a_given_table(spark, key):
    assert methods.queries()[key](spark, SF).inputFiles() or key == "lsh_chain_fixture"  # which ends behind checkpoints
    assert key != "lsh_chain_fixture" or methods.X.derived(spark, SF, methods.X.chain_sql()).inputFiles()


def test_perplexities_of_many_recipes_in_one_pass(spark):
    docs = spark.createDataFrame([("a b a c", True, False), ("b a", True, True), (None, True, True), ("c d", False, None)], "text string, x boolean, y boolean")
    held = spark.createDataFrame([("a b d",), ("c d",)], "text string")
    out = measures.perplexities(docs, ("x", "y"), held)
    got = {r.recipe: (r.tokens, round(r.perplexity, 9)) for r in out.collect()}
    for k in ("x", "y"):
        r = measures.perplexity(measures.train_ngram_lm(docs.where(k)), held).first()
        assert got[k] == (r.tokens, round(r.perplexity, 9))
