r"""Language identification: script ranges narrow the candidates, Viterbi labels spans of mixed text.

A word is a run of letters, with the marks that combine with them, of one script; a run of letters that goes from one known script to another is cut there,
and one of more than `PIECE` letters, as in unspaced scripts, into pieces of that many, each counting as a word.
A piece is scored with the letters that follow it, so every n-gram of a run counts once. The script leaves
the languages that were seen in it; each of those scores the word by the logarithms of its character n-grams. A path over the words of a
text then chooses one language a word, paying a penalty for every switch, so that single odd words do not
break a span while longer stretches in another language become spans of their own. The document's language
is the one that holds most letters; the score is its share of the letters.

Learning takes a bounded sample of labelled rows (about `train_rows`, chosen by a hash of their id, whole
texts); counts are summed on the executors into fixed tables of `BINS` n-gram bins a language.

Defined results: null text or text without letters is `und` with score 0; words in a script that no language
was seen in say nothing, and a text of such words alone gets the most frequent language with score 0; equal
scores go to the first language in code point order; without any labelled row every text is `und`.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, table

BINS = 1 << 15
ORDERS = (1, 2, 3, 4)
PENALTY = 8.0
TRAIN_ROWS = 12_000
#: A language counts as written in a script from this share of its letters on.
SCRIPT_SHARE = 0.02
#: Words of one language are distinguished in memory up to this number, then forgotten; words walked at once.
MEMORY_WORDS = 200_000
SLICE_WORDS = 600_000
LEARN_WORDS = 50_000
LETTERS = re.compile(r"[^\W\d_]+")


def _marked_letters() -> re.Pattern:
    """Runs of letters and of the marks that combine with them; a mark alone is no word."""
    import sys
    import unicodedata

    codes = [c for c in range(0x300, sys.maxunicode + 1) if unicodedata.category(chr(c))[0] == "M"]
    firsts = [c for c, before in zip(codes, [0, *codes]) if c != before + 1]
    lasts = [c for c, after in zip(codes, [*codes[1:], 0]) if c != after - 1]
    marks = "".join(f"{chr(a)}-{chr(b)}" for a, b in zip(firsts, lasts))
    return re.compile(rf"[^\W\d_](?:[^\W\d_]|[{marks}])*")


MARKED_LETTERS = _marked_letters()
#: Script ranges by code point (first, last, script).
SCRIPTS = [
    (0x41, 0x24F, "latin"), (0x370, 0x3FF, "greek"), (0x400, 0x52F, "cyrillic"), (0x530, 0x58F, "armenian"), (0x590, 0x5FF, "hebrew"),
    (0x600, 0x6FF, "arabic"), (0x750, 0x77F, "arabic"), (0x900, 0x97F, "devanagari"), (0x980, 0x9FF, "bengali"), (0xB80, 0xBFF, "tamil"),
    (0xE00, 0xE7F, "thai"), (0x10A0, 0x10FF, "georgian"), (0x1100, 0x11FF, "hangul"), (0x1E00, 0x1EFF, "latin"), (0x1F00, 0x1FFF, "greek"),
    (0x3040, 0x30FF, "kana"), (0x3400, 0x4DBF, "han"), (0x4E00, 0x9FFF, "han"), (0xAC00, 0xD7AF, "hangul"),
]
SCRIPT_NAMES = sorted({s for _, _, s in SCRIPTS}) + ["other"]
#: Most letters of a word; marks of a piece that has letters before it, and between its own and those after it.
PIECE = 64
BEFORE, AFTER = "\x02", "\x03"


def _script_runs() -> re.Pattern:
    """Runs of one known script with the letters of none around them."""
    ranges = lambda names: "".join(f"{re.escape(chr(a))}-{re.escape(chr(b))}" for a, b, s in SCRIPTS if s in names)
    names = SCRIPT_NAMES[:-1]
    every = ranges(names)
    return re.compile("|".join(f"[^{every}]*[{ranges([s])}][^{ranges([x for x in names if x != s])}]*" for s in names) + f"|[^{every}]+")


RUNS = _script_runs()
SEVERAL = re.compile("[\u0300-\U0010ffff]")  # below are letters of one script only, and no marks


def script_of(word: str) -> str:
    for ch in word:
        code = ord(ch)
        for first, last, name in SCRIPTS:
            if first <= code <= last:
                return name
    return "other"


def pieces_of(run: str) -> list[str]:
    """The words of a run of letters, with the marks of pieces."""
    out = []
    for word in RUNS.findall(run):
        ended = word + "$"
        for at in range(0, len(word), PIECE):
            last = at + PIECE >= len(word)
            out.append(BEFORE * (at > 0) + word[at : at + PIECE] + ("" if last else AFTER + ended[at + PIECE : at + PIECE + ORDERS[-1] - 1]))
    return out


def marked_words(text: str | None) -> list[str]:
    """The words of a text, with the marks of pieces."""
    lowered = (text or "").lower()
    several = SEVERAL.search(lowered)
    runs = (MARKED_LETTERS if several else LETTERS).findall(lowered)
    if not several and max(map(len, runs), default=0) <= PIECE:
        return runs
    return [w for r in runs for w in pieces_of(r)]


def letters_of(word: str) -> str:
    return word.removeprefix(BEFORE).partition(AFTER)[0]


def words_of_text(text: str | None) -> list[str]:
    return list(map(letters_of, marked_words(text)))


def bins_of(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """(n-gram bins of all words with their ends marked, number of the word of each); of a piece, those n-grams
    that start at its own letters."""
    marked = [f"^{w}$" if w[:1] != BEFORE and AFTER not in w else "^" * (w[0] != BEFORE) + w.removeprefix(BEFORE).replace(AFTER, "") + "$" * (AFTER not in w) for w in words]
    beyond = np.fromiter((len(w) - w.find(AFTER) - 1 if AFTER in w else 0 for w in words), np.int64, len(words))
    sizes = np.fromiter(map(len, marked), np.int64, len(marked))
    raw = np.frombuffer("".join(marked).encode("utf-32-le"), np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(marked)), sizes)
    left = np.repeat(np.cumsum(sizes), sizes) - np.arange(len(raw))  # symbols from here to the word's end
    own = left > beyond[owner]
    bins, owners = [], []
    for n in ORDERS:
        h = np.full(max(0, len(raw) - n + 1), n, np.uint64)
        for i in range(n):
            h = (h ^ raw[i : i + len(h)]) * np.uint64(0x9E3779B97F4A7C15)
            h ^= h >> np.uint64(31)
        ok = (left[: len(h)] >= n) & own[: len(h)]
        bins.append((h[ok] % np.uint64(BINS)).astype(np.int64))
        owners.append(owner[: len(h)][ok])
    return np.concatenate(bins), np.concatenate(owners)


def _counts(text: str, lang: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words: dict[str, Counter] = {}
        tables: dict = {}
        scripts: Counter = Counter()
        rows: Counter = Counter()

        def drain():
            for lang_, counted in words.items():
                if counted:
                    bins, owner = bins_of(list(counted))
                    weight = np.fromiter(counted.values(), np.int64, len(counted))
                    tables[lang_] = tables.get(lang_, 0) + np.bincount(bins, weight[owner], BINS).astype(np.int64)
                for w, c in counted.items():
                    scripts[lang_, script_of(w)] += c * len(letters_of(w))
            words.clear()

        for batch in batches:
            for t, one in zip(batch.column(text), batch.column(lang).to_pylist()):
                words.setdefault(one, Counter()).update(marked_words(t.as_py()))
                rows[one] += 1
            if sum(map(len, words.values())) > MEMORY_WORDS:
                drain()
        drain()
        out = [(k, "gram", int(b), int(v[b])) for k, v in tables.items() for b in np.flatnonzero(v)]
        out += [(k, "script", SCRIPT_NAMES.index(s), c) for (k, s), c in scripts.items()] + [(k, "rows", 0, c) for k, c in rows.items()]
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*out)], names=["lang", "what", "bin", "n"])

    return lean(run)


class Model:
    """Log-probabilities of n-gram bins by language, and the languages seen in each script."""

    def __init__(self, rows):
        self.langs = sorted({r[0] for r in rows})
        at = {x: i for i, x in enumerate(self.langs)}
        grams = np.full((BINS, len(self.langs)), 0.5, np.float64)
        scripts = np.zeros((len(SCRIPT_NAMES), len(self.langs)))
        self.rows = np.zeros(len(self.langs))
        for lang, what, b, n in rows:
            if what == "gram":
                grams[b, at[lang]] += n
            elif what == "script":
                scripts[b, at[lang]] += n
            else:
                self.rows[at[lang]] += n
        self.grams = np.log(grams / grams.sum(0)).astype(np.float32) if self.langs else grams.astype(np.float32)
        share = scripts / np.maximum(scripts.sum(0), 1)
        self.scripts = {s: share[i] >= SCRIPT_SHARE for i, s in enumerate(SCRIPT_NAMES)}

    def scores(self, words: list[str]) -> np.ndarray:
        """Scores of words by language, the best 0; zeros for a word in an unknown script."""
        bins, owner = bins_of(words)
        got = np.stack([np.bincount(owner, self.grams[bins, k], len(words)) for k in range(len(self.langs))], axis=1)
        allowed = np.stack([self.scripts[script_of(w)] for w in words])
        known = allowed.any(1)
        got = np.where(allowed, got, -np.inf)
        got -= np.where(known, got.max(1), 0)[:, None]
        return np.where(known[:, None], np.maximum(got, -60.0), 0).astype(np.float32)


def fitted(docs: DataFrame, text="text", lang="lang", doc_id="doc_id", train_rows=TRAIN_ROWS) -> Model:
    """Learn from about train_rows of the rows given that have a language."""
    labelled = docs.where(F.col(lang).isNotNull()).select(F.col(text).alias("t"), F.col(lang).alias("l"), F.xxhash64(doc_id, F.lit(10)).alias("h"))
    n = labelled.select("h").count()
    if n > train_rows:
        labelled = labelled.where(F.pmod("h", F.lit(1 << 30)) < int(train_rows / n * (1 << 30)))
    counted = labelled.select("t", "l").mapInArrow(_counts("t", "l"), "lang string, what string, bin bigint, n bigint")
    summed = counted.groupBy("lang", "what", "bin").agg(F.sum("n").alias("n"))  # at most BINS + few rows a language
    return Model([tuple(r) for r in summed.toLocalIterator()])


def viterbi(scores: np.ndarray, lengths: np.ndarray, penalty: float) -> np.ndarray:
    """Best language of every word of many texts at once; the texts' words stand one after another in scores."""
    starts = np.concatenate([[0], np.cumsum(lengths)])[:-1]
    order = np.argsort(-lengths, kind="stable")
    start, size = starts[order], lengths[order]
    out = np.zeros(len(scores), np.int16)
    if not len(scores):
        return out
    back = np.zeros(scores.shape, np.int16)
    k = np.arange(scores.shape[1], dtype=np.int16)
    active = int((size > 0).sum())
    state = scores[start[:active]].copy()
    final = np.zeros(active, np.int16)
    for t in range(1, int(size[0]) + 1):
        now = int(np.searchsorted(-size, -t, side="left"))  # texts with more than t words
        final[now:active] = state[now:active].argmax(1)
        active = now
        if not active:
            break
        state = state[:active]
        best = state.argmax(1).astype(np.int16)
        jump = np.take_along_axis(state, best[:, None].astype(np.int64), 1) - np.float32(penalty)
        stay = state >= jump
        at = start[:active] + t
        back[at] = np.where(stay, k, best[:, None])
        state = np.where(stay, state, jump) + scores[at]
    now = 0
    current = np.zeros(len(size), np.int64)
    for t in range(int(size[0]) - 1, -1, -1):
        more = int(np.searchsorted(-size, -t, side="left"))
        current[now:more] = final[now:more]
        now = more
        at = start[:now] + t
        out[at] = current[:now]
        current[:now] = back[at, current[:now]] if t else current[:now]
    return out


SPANS = "array<struct<first:int,last:int,lang:string>>"
_SPANS_TYPE = pa.list_(pa.struct([("first", pa.int32()), ("last", pa.int32()), ("lang", pa.string())]))


class _Words(dict):
    """Numbers of remembered words, with their scores and lengths."""

    def __init__(self, model: Model):
        super().__init__()
        self.model = model
        self.scores = np.zeros((1024, max(1, len(model.langs))), np.float32)
        self.letters = np.zeros(1024, np.int64)

    def numbers(self, words: list[str]) -> np.ndarray:
        new = sorted(set(words).difference(self))
        if new:
            first = len(self)
            while first + len(new) > len(self.letters):
                self.scores = np.concatenate([self.scores, np.zeros_like(self.scores)])
                self.letters = np.concatenate([self.letters, np.zeros_like(self.letters)])
            if self.model.langs:
                self.scores[first : first + len(new)] = self.model.scores(new)
            self.letters[first : first + len(new)] = [len(letters_of(w)) for w in new]
            self.update(zip(new, range(first, first + len(new))))
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


def _predictor(model: Model, text: str, carry: list[str], penalty: float, spans: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = _Words(model)
        prior = model.langs[int(model.rows.argmax())] if model.langs else "und"

        def flush(batch, first, parts, lengths):
            n, lengths, ids = len(lengths), np.array(lengths, np.int64), np.concatenate(parts)
            scores, size = known.scores[ids], known.letters[ids]
            path = viterbi(scores, lengths, penalty) if model.langs else np.zeros(len(ids), np.int16)
            owner = np.repeat(np.arange(n), lengths)
            telling = scores.any(1) | (len(model.langs) == 1)
            width = max(1, len(model.langs))
            held = np.bincount(owner * width + path, np.where(telling, size, 0), n * width).reshape(n, width)
            total = np.bincount(owner, size, n)
            top = held.argmax(1)
            lang = [("und" if not total[i] or not model.langs else model.langs[top[i]] if held[i, top[i]] else prior) for i in range(n)]
            score = np.where(total > 0, held.max(1) / np.maximum(total, 1), 0.0) if model.langs else np.zeros(n)
            columns = [*(batch.column(c).slice(first, n) for c in carry), pa.array(lang, pa.string()), pa.array(score, pa.float64())]
            if spans:
                ends = np.concatenate([[0], np.cumsum(lengths)])
                found = []
                for i in range(n):
                    p = path[ends[i] : ends[i + 1]]
                    cut = [0, *(np.flatnonzero(p[1:] != p[:-1]) + 1), len(p)] if len(p) else [0]
                    found.append([{"first": int(a), "last": int(b) - 1, "lang": model.langs[p[a]]} for a, b in zip(cut, cut[1:])] if model.langs else [])
                columns.append(pa.array(found, _SPANS_TYPE))
            return pa.RecordBatch.from_arrays(columns, names=[*carry, "lang_pred", "lang_score"] + ["lang_spans"] * spans)

        for batch in batches:
            texts, first, lengths, parts, waiting = batch.column(text), 0, [], [], []
            for i in range(batch.num_rows):
                words = marked_words(texts[i].as_py())
                waiting += words
                lengths.append(len(words))
                last = i + 1 == batch.num_rows
                if len(waiting) >= LEARN_WORDS or last:
                    parts.append(known.numbers(waiting))
                    waiting = []
                if last or sum(map(len, parts)) >= SLICE_WORDS and not waiting:
                    yield flush(batch, first, parts, lengths)
                    first, lengths, parts = i + 1, [], []
                    if len(known) > MEMORY_WORDS:
                        known.clear()

    return lean(run)


def identified(docs: DataFrame, model: Model, text="text", carry=None, penalty=PENALTY, spans=True) -> DataFrame:
    """The carried columns (all by default), lang_pred, lang_score and lang_spans (word numbers from 0)."""
    carry = [c for c in docs.columns if c not in ("lang_pred", "lang_score", "lang_spans")] if carry is None else list(carry)
    schema = [f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in carry] + ["lang_pred string", "lang_score double"] + [f"lang_spans {SPANS}"] * spans
    return docs.select(*dict.fromkeys([*carry, text])).mapInArrow(_predictor(model, text, carry, penalty, spans), ", ".join(schema))


def held_out(doc_id="doc_id"):
    """Fixed fold: documents never learnt from."""
    return F.pmod(F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")), F.lit(3)) == 1


def contract_model(docs: DataFrame) -> Model:
    return fitted(docs.where(~held_out()))


def op10_language(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    got = identified(docs, contract_model(docs), carry=["doc_id"], spans=False)
    return got.select("doc_id", held_out().alias("held_out"), "lang_pred", F.col("lang_score").alias("score"))


__all__ = ["Model", "fitted", "identified", "viterbi", "held_out", "contract_model", "op10_language"]
