"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing names: every operator, every stage."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from anchorseek.llm import langid, licenses, lsh_forest, mixing, quality, secrets, token_files, toxicity, url_rules, winnow

LABELS = "doc_id long, quality int, toxic int, _y int"


def tokenizer():
    public = pytest.importorskip("public_tokenizers")
    return public.path("byte_bpe_50k.json")


def test_quality(ready, odd, none):
    labels = ready.createDataFrame([(1, 1, 0, 1), (1, 0, 0, 1), (None, 1, 0, 1), (5, None, 1, 1)], LABELS)
    got = quality.judged(odd, labels).collect()
    assert len(got) == odd.count()
    by = {r.doc_id: r for r in got}
    assert by[2].n_words == by[3].n_words == by[4].n_words == 0 and by[2].base_failed and not by[2].kept
    assert by[5].n_words == 30_000 and by[1].kept
    assert quality.judged(none, labels).count() == 0 == quality.judged(none, labels.limit(0)).count()


def test_near_duplicates(odd, none):
    got = lsh_forest.near_duplicates(odd).collect()
    assert len(got) == odd.count()
    by = {r.doc_id: r for r in got}
    assert by[2].n_shingles == by[3].n_shingles == by[4].n_shingles == 0 and by[2].kept and by[3].component_id == 3
    assert by[11].n_shingles == 1 and by[None].component_id is None and by[None].kept
    assert [r.kept for r in got if r.doc_id == 6] == [True, True]
    assert lsh_forest.near_duplicates(none).count() == 0


def test_tokens(ready, odd, none, tmp_path):
    for name, df in (("odd", odd), ("none", none)):
        token_files.write_tokens(df, tokenizer(), str(tmp_path / name))
        got = token_files.token_index(ready, str(tmp_path / name)).collect()
        assert len(got) == df.count()
    by = {r.doc_id: r for r in token_files.token_index(ready, str(tmp_path / "odd")).collect()}
    assert by[2].n_tokens == by[3].n_tokens == 1 and by[None].start == 0


def test_decontaminate(ready, odd, none):
    bench = ready.createDataFrame([(1, None, 1), (2, "", 1), (3, "one", 1), (None, "null language", 1), (3, "one", 1)], "item_id long, text string, _mark int")
    for limit in (1 << 20, -1):
        got = winnow.marked(odd, bench, broadcast_chars=limit).collect()
        by = {r.doc_id: r["_mark"] for r in got}
        assert len(got) == odd.count() and by[11]["items"] == ["3"] and by[7].n_hit == 2 and by[7]["items"] == [] and by[2].n_words == 0
        assert winnow.marked(none, bench, broadcast_chars=limit).count() == 0
        assert all(r["_mark"].n_hit == 0 for r in winnow.marked(odd, bench.limit(0), broadcast_chars=limit).collect())


def test_toxicity(ready, odd, none):
    rows = [(1, 1, 0, 0), (5, 0, 1, 0), (6, 1, None, 0), (None, 1, 1, 0)]
    cats = {"poor": F.col("quality") == 0, "toxic": F.col("toxic") == 1}
    for labels in (ready.createDataFrame(rows, LABELS), ready.createDataFrame([], LABELS)):
        chain = toxicity.fitted(odd, labels, cats)
        got = toxicity.scored(odd, chain).collect()
        assert len(got) == odd.count() and all(0 <= r.p_toxic <= 1 and 0 <= r.p_poor <= 1 for r in got)
        assert toxicity.scored(none, chain).count() == 0


def test_licenses(odd, none):
    got = licenses.scanned(odd).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == odd.count() and by[2].n_words == 0 and by[2].first_word is None and by[2].labels == "" and by[None].n_words == 6
    assert licenses.scanned(none).count() == 0


def test_secrets(ready, odd, none):
    forest = secrets.fitted(secrets.synthetic_findings(ready, 400), trees=3, depth=3)
    assert secrets.scanned(odd, forest).count() == odd.count() and secrets.scanned(none, forest).count() == 0
    empty = secrets.fitted(secrets.synthetic_findings(ready, 400).limit(0))
    assert secrets.scanned(odd, empty).count() == odd.count()


def test_mixing(odd, none):
    got = mixing.with_taken(odd).collect()
    assert len(got) == odd.count() and all(r.taken <= 3 * r.size for r in got)
    assert mixing.with_taken(none).count() == 0 and mixing.mixed(none).count() == 0
    assert mixing.mixed(odd).columns == odd.columns


def test_language(odd, none):
    model = langid.fitted(odd.where("lang IS NOT NULL"))
    got = langid.identified(odd, model).collect()
    by = {r.doc_id: r for r in got}
    assert len(got) == odd.count() and by[2].lang_pred == by[10].lang_pred == "und" and by[2].lang_score == 0
    assert langid.identified(none, model).count() == 0
    blank = langid.fitted(none)
    assert {r.lang_pred for r in langid.identified(odd, blank).collect()} == {"und"}


def test_urls(ready):
    rows = [(1, "http://A.Example.NET/en/x"), (1, "http://A.Example.NET/en/x"), (2, None), (3, "no scheme"), (4, "://"), (5, "x://net"), (6, "s://b.net?q/"), (None, "http://net/")]
    pages = ready.createDataFrame([(*r, 1, 1) for r in rows], "page_id long, url string, _rev int, rule int")
    rules = ready.createDataFrame([("net", "/", "block"), ("example.net", "/en/", "allow"), ("net", "/", "block"), (None, "/", "block"), ("b.net", None, "allow")], "host string, path string, verdict string")
    got = url_rules.filter_urls(pages, rules).collect()
    by = {r.page_id: r for r in got}
    assert len(got) == len(rows) and by[1].host == "a.example.net" and by[1].rule == "example.net/en/"
    assert (by[2].host, by[2].path, by[2].rule, by[2].verdict) == ("", "", None, "allow")
    assert by[5].rule is None and by[6].rule == "b.net" and by[None].verdict == "block"
    assert url_rules.filter_urls(pages.limit(0), rules).count() == 0
    assert {r.verdict for r in url_rules.filter_urls(pages, rules.limit(0)).collect()} == {"allow"}


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages(ready, odd, none, name):
    tokenizer()
    stage = dict(corpus_pipeline.STAGES)[name]
    for df in (odd, none):
        got = stage(ready, df, "/root/testdata/sf0.001")
        if name != "tokens":
            assert got.columns == df.columns
        assert got.count() <= 3 * df.count()


def test_pipeline_runs(ready):
    tokenizer()
    got = corpus_pipeline.run(ready, "/root/testdata/sf0.001").collect()
    got.sort(key=lambda r: r.start)
    total = 0
    for r in got:
        assert r.start == total
        total += r.n_tokens
