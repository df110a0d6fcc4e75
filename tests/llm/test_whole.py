"""Whole jobs on small fixtures: what an operator must not leave out."""

import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from anchorseek.llm import langid, lsh_forest, quality, token_files

SF = "/root/testdata/sf0.001"


def test_stage_links_from_080_on(ready):
    r = random.Random(5)
    texts = []
    for _ in range(30):
        w = [f"w{r.randrange(10**6)}" for _ in range(60)]
        texts.append(" ".join(w))
        texts.append(" ".join(w[:30] + ["other"] + w[31:]))  # 51 of 61 shingles: 0.836
        texts.append(" ".join(w[:20] + ["other"] + w[21:40] + ["more"] + w[41:]))  # 46 of 66: 0.70
    df = ready.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    kept = {x.doc_id for x in corpus_pipeline.drop_near_duplicates(ready, df, SF).collect()}
    assert kept == {i for i in range(len(texts)) if i % 3 != 1}
    assert (1 - 0.8 ** lsh_forest.DEPTHS[0]) ** lsh_forest.TREES < 1e-5


def test_added_tokens_are_encoded_as_by_the_library(ready, tmp_path):
    from tokenizers import Tokenizer

    path = pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json")
    plain = Tokenizer.from_file(path)
    texts = ["a <|endoftext|> b", "no such thing", "<|endoftext|>", "x<|endoftext|><|endoftext|>\n y", "<|endof", "text|> cut over two rows", "日本 <|endoftext|>", ""]
    want = [np.array(plain.encode(t, add_special_tokens=False).ids + [0], "<u4") for t in texts]
    encoder = token_files.PieceEncoder(path)
    assert [encoder.encode(t) for t in texts] == [w[:-1].tobytes() for w in want]
    df = ready.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    token_files.write_tokens(df, path, str(tmp_path / "added"))
    got = sorted((r.doc_id, r.start, r.n_tokens, r.ids_crc32) for r in token_files.token_index(ready, str(tmp_path / "added")).collect())
    starts = np.cumsum([0] + [len(w) for w in want])
    assert got == [(i, starts[i], len(w), zlib.crc32(w.tobytes())) for i, w in enumerate(want)]
    assert want[0].tolist() == [64, 220, 50256, 275, 0]


def test_quality_cutoffs_with_a_few_hundred_labels(ready):
    r = random.Random(6)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(r.randint(2, 9)))
    texts, labels = [], []
    for lang in ("aa", "bb", "cc", "dd"):
        for i in range(312 + 40):
            bad = i >= 312
            n = len(texts)
            texts.append((n, " ".join(word() + (" #" if bad else "") for _ in range(40)), lang))
            labels.append((n, 0 if bad else 1))
    texts += [(10_000 + i, " ".join(word() + " #" for _ in range(40)), "ee") for i in range(20)]
    labels += [(10_000 + i, int(i < 10)) for i in range(20)]
    df, known = ready.createDataFrame(texts, "doc_id long, text string, lang string"), ready.createDataFrame(labels, "doc_id long, quality int")
    got = {(x.q, x.lang == "ee"): x.s for x in quality.judged(df, known).join(known.withColumnRenamed("quality", "q"), "doc_id").withColumnRenamed("_stratum", "lang").groupBy("q", "lang").agg(F.avg(F.col("kept").cast("double")).alias("s")).collect()}
    assert got == {(1, False): 1.0, (0, False): 0.0, (1, True): 1.0, (0, True): 1.0}  # ee: too few labels
    # the path and its test, against a plain version
    measures = quality.measured(df, carry=["doc_id"], stratum="lang")
    holdout = quality.labelled(measures, known)
    chosen = {}
    for x in quality.thresholds(holdout).collect():
        chosen.setdefault(x["_stratum"], {})[x.rule] = (x.cutoff, x.n_good, x.n_rejected, x.n_bad, x.n_bad_rejected)
    assert chosen == plain_thresholds([x.asDict() for x in holdout.collect()]) and set(chosen) == {"aa", "bb", "cc", "dd"}


def plain_thresholds(rows):
    from math import comb

    out, strata = {}, {x["_stratum"] for x in rows if x["_good"]}
    for stratum in strata:
        good, bad = ([x for x in rows if x["_stratum"] == stratum and x["_good"] == g] for g in (True, False))
        path, gone = [], set()
        for i in range(12):
            for rule, cuts in quality.GRID.items():
                new = {x["doc_id"] for x in bad if x[rule] > cuts[i]} - gone
                if new:
                    path.append((rule, cuts[i]))
                    gone |= new
        now = {}
        for rule, cut in path:
            step = now | {rule: cut}
            k, n = sum(any(x[r] > c for r, c in step.items()) for x in good), len(good)
            if sum(comb(n, j) * quality.RISK**j * (1 - quality.RISK) ** (n - j) for j in range(k + 1)) > quality.LEVEL / len(strata):
                break
            now = step
            out[stratum] = {r: (c, n, k, len(bad), sum(any(x[q] > d for q, d in now.items()) for x in bad)) for r, c in now.items()}
    return out


def test_language_reads_every_letter(ready):
    r = random.Random(8)
    run = lambda letters, n: "".join(r.choice(letters) for _ in range(n))
    for n in (1, 63, 64, 65, 66, 67, 68, 128, 129, 500):
        word = run("abcdefgh", n)
        pieces = langid.pieces_of(word)
        assert "".join(map(langid.letters_of, pieces)) == word and max(len(langid.letters_of(p)) for p in pieces) <= 64
        assert sorted(langid.bins_of(pieces)[0]) == sorted(langid.bins_of([word])[0])  # every n-gram once
    assert langid.words_of_text("abcабвabc, ªx日本テスト") == ["abc", "абв", "abc", "ªx", "日本", "テスト"]
    letters = {"aa": "abcdefgh", "bb": "mnopqrst", "cc": "абвгдежз"}
    learnt = [(i, " ".join(run(letters[k], 6) for _ in range(60)), k) for i, k in enumerate(["aa", "bb", "cc"] * 10)]
    model = langid.fitted(ready.createDataFrame(learnt, "doc_id long, text string, lang string"))
    texts = [(1, run(letters["aa"], 128) + run(letters["bb"], 448)), (2, run(letters["aa"], 30) + run(letters["cc"], 90)), (3, run(letters["bb"], 576))]
    got = {x.doc_id: x for x in langid.identified(ready.createDataFrame(texts, "doc_id long, text string"), model).collect()}
    assert [(s.first, s.last, s.lang) for s in got[1].lang_spans] == [(0, 1, "aa"), (2, 8, "bb")]
    assert (got[1].lang_pred, got[1].lang_score) == ("bb", 448 / 576)
    assert (got[2].lang_pred, got[2].lang_score) == ("cc", 0.75) and (got[3].lang_pred, got[3].lang_score) == ("bb", 1.0)
