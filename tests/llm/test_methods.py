"""The named methods themselves, against plain versions: orders of trees, diagonals, groups of bytes, findings."""

import glob
import random
import re

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from anchorseek.llm import common, langid, licenses, lsh_forest, quality, secrets, token_files, toxicity, url_rules, winnow

ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


# ---------------------------------------------------------------- LSH forest

def test_common_prefixes_of_neighbours():
    r = np.random.default_rng(1)
    sig = r.integers(0, 2, (400, lsh_forest.DEPTH)).astype(np.uint32)
    keys = np.array([lsh_forest.tree_keys(s, 1)[0] for s in sig])
    order = np.lexsort((keys[:, 1].view(np.int64), keys[:, 0].view(np.int64)))
    got = lsh_forest.common_prefix(keys[order, 0], keys[order, 1])
    for a, b, g in zip(order, order[1:], got[1:]):
        same = next((i for i in range(lsh_forest.DEPTH) if sig[a, i] != sig[b, i]), lsh_forest.DEPTH)
        assert g == (same if same >= lsh_forest.PREFIX else 0)


def test_cuts_fall_where_prefixes_are_short():
    prefix = np.array([0, 8, 8, 8, 5, 8, 8, 6, 8, 8, 8, 8, 4, 8, 8, 8])
    ones = np.ones(16, np.int64)
    assert lsh_forest.cuts_of(prefix, ones, 6, 100) == [0, 4, 7, 12]
    for group, room in ((3, 1000), (5, 7), (16, 4), (100, 10**9)):
        cuts = lsh_forest.cuts_of(prefix, ones, group, room) + [16]
        assert cuts[0] == 0 and all(0 < b - a <= group and (b - a <= max(2, room)) for a, b in zip(cuts, cuts[1:]))


def near_brute(texts, p, q):
    words = {i: re.findall(r"[^\x20\x09-\x0D]+", t) for i, t in texts.items()}
    sets = {i: {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set() for i, w in words.items()}
    part = {i: i for i in sets}

    def root(i):
        while part[i] != i:
            i = part[i]
        return i

    for a in sets:
        for b in sets:
            if a < b and sets[a] and q * len(sets[a] & sets[b]) >= p * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                part[y] = x
    return {i: root(i) for i in sets}


def test_regions_over_many_ranges(ready, monkeypatch):
    """One large family over 40 ranges, groups of 8, and little room: borders, cuts, hubs and blocks all act."""
    monkeypatch.setattr(lsh_forest, "GROUP", 8)
    r = random.Random(3)
    base = [f"w{i}" for i in range(80)]
    texts = []
    for _ in range(120):
        w = list(base)
        for _ in range(r.randint(0, 4)):
            w[r.randrange(80)] = f"x{r.randrange(10**6)}"
        texts.append(" ".join(w))
    texts += [" ".join(f"y{r.randrange(10**6)}" for _ in range(40)) for _ in range(60)]
    rows = list(enumerate(texts))
    df = ready.createDataFrame(rows, "doc_id long, text string")
    before = ready.conf.get("spark.sql.shuffle.partitions")
    ready.conf.set("spark.sql.shuffle.partitions", "40")
    try:
        for room in (200, 10**9):
            got = {x.doc_id: x.component_id for x in lsh_forest.near_duplicates(df, link=(80, 100), room=room).collect()}
            assert got == near_brute(dict(rows), 80, 100)
    finally:
        ready.conf.set("spark.sql.shuffle.partitions", before)


def test_candidates_beyond_the_bitmap(ready, monkeypatch):
    monkeypatch.setattr(lsh_forest, "MOST_BITS", 0)
    texts = {i: " ".join(f"w{j}" for j in range(50)) + (f" x{i}" if i % 2 else "") for i in range(20)}
    df = ready.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {x.component_id for x in lsh_forest.near_duplicates(df).collect()} == {0}
    with pytest.raises(TypeError):
        lsh_forest.near_duplicates(df.withColumn("doc_id", F.col("doc_id").cast("string")))


def test_settled_tables_can_be_removed(ready, tmp_path):
    import os

    df = common.settled(ready.range(5).toDF("x"), "t")
    path = df._settled
    assert os.path.isdir(path)
    common.discard(df, ready.range(1))
    assert not os.path.exists(path)


# ---------------------------------------------------------------- token files

def test_columns_encode_like_the_library():
    e = token_files.PieceEncoder(pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json"))
    r = random.Random(5)
    alphabet = list(" \n\t'.,a1sé½ĳª_\x1c\xa0\x85Жµ²́日 !tll reve'dmK") + ["<|endoftext|>", "'re", " 's", "  ", "\xa0\xa0", "é'll"]
    for n in (1, 3, 40, 400):
        for _ in range(40):
            texts = [None if r.random() < 0.02 else "".join(r.choice(alphabet) for _ in range(r.randint(0, 30))) for _ in range(n)]
            ids, lengths = e.encode_all(pa.array(texts, pa.string()), 0)
            want = [np.frombuffer(e.whole(t or ""), "<u4").tolist() + [0] for t in texts]
            assert lengths.tolist() == [len(w) for w in want] and ids.tolist() == [x for w in want for x in w]
    sliced = pa.array(["x y", "ab's", None, "日 a"]).slice(1, 3)
    assert e.encode_all(sliced, 0)[0].tolist() == [x for t in ("ab's", "", "日 a") for x in [*np.frombuffer(e.whole(t), "<u4").tolist(), 0]]


@pytest.mark.parametrize("encoding", ["dictionary", "delta"])
def test_files_have_the_stated_form(ready, tmp_path, encoding):
    path = pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json")
    docs = ready.createDataFrame([(i, f"word{i} and some more of {i % 7} " * 30) for i in range(3000)], "doc_id long, text string")
    token_files.write_tokens(docs.coalesce(1), path, str(tmp_path / encoding), encoding=encoding, row_group_bytes=1 << 13, page_bytes=1 << 12, page_rows=50)
    groups = rows = 0
    firsts = []
    for f in sorted(glob.glob(f"{tmp_path}/{encoding}/part-*.parquet")):
        meta = pq.ParquetFile(f).metadata
        for g in range(meta.num_row_groups):
            group = meta.row_group(g)
            for c in range(group.num_columns):
                col = group.column(c)
                assert col.has_offset_index and col.has_column_index and col.compression == "SNAPPY"
                if col.path_in_schema.startswith("ids"):
                    if encoding == "delta":
                        assert "DELTA_BINARY_PACKED" in col.encodings and not col.has_dictionary_page
                    else:
                        assert col.has_dictionary_page and "RLE_DICTIONARY" in col.encodings
                if col.path_in_schema == "doc_id":
                    firsts.append((col.statistics.min, col.statistics.max))
            rows += group.num_rows
        groups += meta.num_row_groups
    assert rows == 3000 and groups > 8
    assert all(a[1] < b[0] for a, b in zip(firsts, firsts[1:]))  # in order, so readers skip groups by their bounds


# ---------------------------------------------------------------- licences

def labels_of(ready, texts):
    df = ready.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [r.labels for r in sorted(licenses.scanned(df).collect(), key=lambda r: r.doc_id)]


def test_licence_versions_are_told_apart(ready):
    cases = {
        "Licensed under CC BY-NC 4.0.": "cc-by,cc-by-nc-4.0",
        "CC BY 4.0": "cc-by,cc-by-4.0",
        "CC BY-SA 4.0": "cc-by,cc-by-sa-4.0",
        "CC BY-ND 4.0": "cc-by,cc-by-nd-4.0",
        "CC BY-NC-SA 4.0": "cc-by,cc-by-nc-sa-4.0",
        "GNU General Public License version 2": "gpl,gpl-2.0",
        "This work is licensed under the GNU General Public License, version 3.": "gpl,gpl-3.0",
        "GNU General Public License version 4": "gpl",
        "GNU Lesser General Public License, version 2.1": "gpl,lgpl-2.1",
        "GNU Lesser General Public License": "gpl,lgpl",
        "GNU Affero General Public License version 3": "agpl-3.0,gpl",
        "Released under the MIT License.": "mit",
        "Released under the terms of the MIT License.": "",
        "Licensed under the Apache License, Version 2.0.": "apache-2.0",
        "Licensed under the Apache License, Version 1.1.": "",
        "CC BY 4.0 or General Public License version 3": "cc-by,cc-by-4.0,gpl,gpl-3.0",
        "This is free and unencumbered code released into the public domain": "unlicense",
    }
    assert dict(zip(cases, labels_of(ready, list(cases)))) == cases


def licence_brute(words, templates, cover=licenses.COVER, drift=licenses.DRIFT, k=licenses.K):
    """Spans (cover, grams, first, last, label) of the templates in a text, by plain loops."""
    spans = []
    for text, label in templates:
        want, must = licenses._wordings(text)
        n = len(want) - k + 1
        lines = {}
        for p in range(len(words) - k + 1):
            for q in range(n):
                if words[p : p + k] == want[q : q + k]:
                    lines.setdefault(p - q, []).append((p, q))
        group = []
        for d in sorted(lines):
            full = len({q for _, q in lines[d]}) == n
            first = min(p for p, _ in lines[d])
            if group and not full and not group[-1][1] and d - group[-1][0] <= drift and first - group[-1][2] <= n + drift:
                group.append((d, full, first))
            else:
                if group:
                    spans.append((text, label, n, must, [d for d, _, _ in group], lines))
                group = [(d, full, first)]
        if group:
            spans.append((text, label, n, must, [d for d, _, _ in group], lines))
    out = []
    for _, label, n, must, ds, lines in spans:
        votes = [x for d in ds for x in lines[d]]
        share = len({q for _, q in votes}) / n
        first, last = min(p for p, _ in votes), max(p for p, _ in votes) + k - 1
        if share >= cover and last - first < n + k + drift and any(must <= {q for _, q in lines[d]} for d in ds):
            out.append((-share, -n, first, last, label))
    kept = []
    for s in sorted(set(out)):
        if not any(t[2] <= s[3] and s[2] <= t[3] for t in kept):
            kept.append(s)
    return kept


def test_licence_spans_against_plain_loops(ready):
    r = random.Random(11)
    parts = [re.sub(r"[\[\]]", "", t) for t, _ in licenses.TEMPLATES] + ["cc by", "all rights reserved", "version 2", "4 0", "nc", "general public license"]
    texts = []
    for _ in range(250):
        words = []
        for _ in range(r.randint(1, 5)):
            w = r.choice(parts).split()
            for _ in range(r.randint(0, 2)):
                i = r.randrange(len(w) + 1)
                w = w[:i] + (["odd"] if r.random() < 0.5 else []) + w[i + (r.random() < 0.4) :]
            words += w + ["filler"] * r.randint(0, 3)
        texts.append(" ".join(words).title())
    df = ready.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for g in licenses.scanned(df).collect():
        words = ALNUM.findall(texts[g.doc_id].translate(LOWER))
        base = [label for phrase, label in licenses.BASE.items() for p in range(len(words)) if words[p : p + len(phrase.split())] == phrase.split()]
        spans = licence_brute(words, licenses.TEMPLATES)
        assert g.n_base == len(base)
        assert g.labels == ",".join(sorted({*base, *(s[4] for s in spans)})), texts[g.doc_id]
        assert abs(g.score - max([1.0 if base else 0.0, *(-s[0] for s in spans)])) < 1e-9


# ---------------------------------------------------------------- secrets

def test_secrets_of_other_formats(ready):
    """Formats that the generated findings do not hold: precision and recall."""
    r = random.Random(2)
    text = lambda letters, n: "".join(r.choice(letters) for _ in range(n))
    low, num = "abcdefghijklmnopqrstuvwxyz", "0123456789"
    any_ = low + low.upper() + num
    secret = [
        lambda: f'db_password = "{text(any_, 9)}!{text(num, 2)}"', lambda: f"Authorization: Bearer eyJ{text(any_, 40)}.{text(any_, 30)}.{text(any_, 43)}", lambda: f"AUTH_TOKEN={text(any_, 24)}",
        lambda: f"glpat-{text(any_, 20)}", lambda: f"passwd: {text(any_, 5)}#{text(any_, 5)}", lambda: f"xoxb-{text(num, 12)}-{text(any_, 24)}",
    ]
    clean = [
        lambda: f"see https://docs.{text(low, 8)}.org/{text(low, 6)}/{text(low, 9)}.html", lambda: f"git-svn-id {text('0123456789abcdef', 40)}", lambda: f"ISBN 978-{text(num, 1)}-{text(num, 4)}-{text(num, 4)}-{text(num, 1)}",
        lambda: f"+49-{text(num, 4)}-{text(num, 9)}", lambda: f"{text(low, 9)}_{text(low, 9)}_{text(low, 6)}", lambda: f"etag: {text('0123456789abcdef', 32)}",
    ]
    rows = [(i, f"the start {(secret if i % 2 else clean)[i // 2 % 6]()} and the end") for i in range(600)]
    docs = ready.read.parquet("/root/testdata/sf0.01/documents.parquet")
    words = secrets.dictionary(docs)
    forest = secrets.fitted(secrets.synthetic_findings(ready), words=words)
    got = {x.doc_id: x.n for x in secrets.scanned(ready.createDataFrame(rows, "doc_id long, text string"), forest, carry=["doc_id"]).select("doc_id", F.size("secrets").alias("n")).collect()}
    hit = sum(got[i] > 0 for i in got if i % 2)
    wrong = sum(got[i] > 0 for i in got if i % 2 == 0)
    print("recall", hit / 300, "precision", hit / (hit + wrong))
    assert hit / 300 >= 0.8 and hit / (hit + wrong) >= 0.9


def test_dictionary_is_the_corpus(ready):
    df = ready.createDataFrame([(i, "common words stand Everywhere" + (" rareword" if i == 3 else "") + " abc") for i in range(40)], "doc_id long, text string")
    words = secrets.dictionary(df)
    told = lambda w: ready.range(1).select((secrets._covered(F.lit(w), words)).alias("n")).first().n
    assert [told(w) for w in ("common", "everywhere", "Everywhere", "common_words9stand", "rareword", "abc")] == [6, 10, 10, 16, 0, 0]
    assert secrets.dictionary(df.limit(0)) == bytes(secrets.WORD_BITS // 8)


# ---------------------------------------------------------------- language, toxicity, quality, urls

def test_many_languages_and_marks(ready):
    r = np.random.default_rng(4)
    scores = -r.random((60, 300)).astype(np.float32)
    scores[:, 250] = 0
    assert langid.viterbi(scores, np.array([20, 40]), 2.0).tolist() == [250] * 60
    assert langid.words_of_text("हिन्दी भाषा") == ["हिन्दी", "भाषा"] and langid.words_of_text("́ áb") == ["áb"]
    learnt = [(i, f"{chr(97 + i % 26)}{chr(97 + i // 26)}{chr(97 + i % 26)} " * 40, f"l{i:03d}") for i in range(200)]
    model = langid.fitted(ready.createDataFrame(learnt, "doc_id long, text string, lang string"))
    got = langid.identified(ready.createDataFrame(learnt, "doc_id long, text string, lang string"), model).select("lang", "lang_pred").collect()
    assert len(model.langs) == 200 and all(x.lang == x.lang_pred for x in got)
    same = [(1, "ab " * 30, "aa"), (2, "ab " * 30, "bb")]
    tied = langid.fitted(ready.createDataFrame(same, "doc_id long, text string, lang string"))
    assert langid.identified(ready.createDataFrame([(1, "ab ab")], "doc_id long, text string"), tied).first().lang_pred == "aa"


def test_long_words_are_read_whole():
    r = random.Random(1)
    kana = [chr(c) for c in range(0x3041, 0x3090)]
    start = "".join(r.choice(kana) for _ in range(64))
    a, b = (start + "".join(r.choice(kana) for _ in range(10_000)) for _ in range(2))
    fa, fb = (set(toxicity.features_of([w])[0].tolist()) for w in (a, b))
    assert len(fa & fb) < 0.2 * len(fa) and len(fa) > 10_000


def test_training_reads_all_words(ready):
    long_ = " ".join(f"word{chr(97 + i % 26)}{chr(97 + i // 26 % 26)}{chr(97 + i // 676)}" for i in range(5000))
    docs = ready.createDataFrame([(i, long_ + (" vilest" if i % 2 else "")) for i in range(60)], "doc_id long, text string")
    labels = ready.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, toxic int")
    chain = toxicity.fitted(docs, labels, {"toxic": F.col("toxic") == 1})
    got = toxicity.scored(docs, chain, carry=["doc_id"]).collect()
    assert all((x.p_toxic >= chain.cutoffs[-1]) == bool(x.doc_id % 2) for x in got)


def test_repeated_rows_count_once_in_the_holdout(ready):
    texts = [(i, f"w{i} " * 3 + " ".join(f"x{i}y{j}" for j in range(30)), "en") for i in range(10)]
    df = ready.createDataFrame(texts * 3, "doc_id long, text string, lang string")
    known = ready.createDataFrame([(i, 1) for i in range(10)], "doc_id long, quality int")
    assert quality.labelled(quality.measured(df, carry=["doc_id"], stratum="lang"), known).count() == 10


def test_url_rules_of_any_letters_and_length(ready):
    rules = ready.createDataFrame([("Ünet.COM", "/a/", "block"), ("aa.com", "/x/y", "allow"), ("com", "/x/y/ab", "block")], "host string, path string, verdict string")
    long_ = "http://" + "s." * 20_000 + "Ünet.com/a/" + "p" * 100_000
    pages = ready.createDataFrame([(1, "http://x.Ünet.com/a/b"), (2, "http://x.ünet.com/a/b"), (3, long_), (4, "http://aa.com/x/y/ab")], "page_id long, url string")
    got = {x.page_id: x for x in url_rules.filter_urls(pages, rules).collect()}
    assert [got[i].verdict for i in (1, 2, 3)] == ["block", "allow", "block"]
    assert got[4].rule == "aa.com/x/y" or len(got[4].rule) == len("com/x/y/ab")  # equal length


def test_shuffled_marks_equal_the_broadcast_ones(ready):
    r = random.Random(9)
    bench = ready.createDataFrame([(i, " ".join(f"b{r.randrange(9)}" for _ in range(n))) for i, n in enumerate([3, 13, 30])], "item_id long, text string")
    docs = ready.createDataFrame([(i % 50, " ".join(f"b{r.randrange(9)}" for _ in range(60)) if i % 3 else None) for i in range(80)], "doc_id long, text string")
    rows = lambda limit: sorted((x.doc_id, x._mark.n_words, x._mark.n_hit, tuple(x._mark["items"])) for x in winnow.marked(docs, bench, carry=["doc_id"], broadcast_chars=limit).collect())
    assert rows(1 << 20) == rows(-1)
