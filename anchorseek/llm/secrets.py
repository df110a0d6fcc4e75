r"""Secret scan with a random forest, in DataFrame functions only.

Candidates are long unbroken strings with a digit or mixed case, and the values, short ones and ones with
symbols too, that are assigned to secret names. Each is described by its length, its character classes and the
transitions between them, the share of it that dictionary words cover, signs of a path, known prefixes of
providers' keys, and the words before and after. A random forest trained on labelled findings then drops the
false positives (digests, ids, numbers, file names, long words, placeholders). The trained trees are written out
as nested CASE expressions, so scoring runs where the texts are read, one row a document, without a shuffle.

The dictionary is that of the corpus: words that at least `WORD_SHARE` of the documents hold, counted over all
of them, as a bitmap of `WORD_BITS` bits over their hashes. As many words as documents hold words on average,
divided by `WORD_SHARE`, can be in it at most; the chance that another word counts as one is the bitmap's fill.

Labelled findings are a table (context columns and a 0/1 label). Where a corpus has none,
`synthetic_findings` makes a bounded one: keys and passwords in several formats behind assignments to secret
names, keys of providers without a name, and look-alikes behind names of digests, ids, paths and in running text.

Defined results: null or empty text has no candidates; repeated documents each get a row; a candidate found
twice counts twice; without labelled findings of both kinds every candidate gets the share of positive labels;
without a dictionary no word covers anything.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bind, table, words_of

SHORTEST = 16
TREES = 25
DEPTH = 7
CUTOFF = 0.5
CANDIDATE = r"[A-Za-z0-9_+/=.\-]{16,}"
#: Names before a secret, names before something that looks like one, prefixes of providers' keys.
SECRET_NAMES = r"(?i)(token|secret|passw(?:or)?d|passwort|pwd|api[_-]?key|apikey|access[_-]?key|private[_-]?key|auth|credential|bearer)"
OTHER_NAMES = r"(?i)(sha\d*|md5|digest|checksum|commit|hash|etag|uuid|guid|rev(ision)?|integrity|build|version|session|trace|order|invoice|card|phone|isbn|id)\b"
PREFIXES = r"^(AKIA|ASIA|ghp_|gho_|glpat-|xox[abp]-|AIza|sk_live_|sk-|eyJ)"
#: A value behind a secret name and a sign, in one word; a value that is a word of its own.
JOINED = SECRET_NAMES + r"[\w\-]*[\"']?[=:]+[\"']?([^\"'=,;]{6,})"
VALUE = r"^[\"'(]*([^\"',;()]{6,})"
WORD_SHARE = 0.002
LEAST_DOCS = 3
WORD_BITS = 1 << 19
FEATURES = ["length", "digits", "upper", "lower", "marks", "symbols", "turns", "distinct", "hex", "covered", "slashes", "dots", "extension", "prefixed", "named_secret", "named_other", "assigned", "quoted", "prose_before", "prose_after"]


def _count(text, pattern: str):
    return F.regexp_count(text, F.lit(pattern)).cast("double")


def dictionary(docs: DataFrame, text="text", share: float = WORD_SHARE) -> bytes:
    """A bitmap of the words (4 to 30 letters) that at least a share of the documents hold, and LEAST_DOCS of them."""
    words = F.filter(F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"[^\p{L}]+"), lambda w: (F.length(w) >= 4) & (F.length(w) <= 30))
    held = docs.select(F.explode(F.array_distinct(words)).alias("w")).groupBy("w").agg(F.count(F.lit(1)).alias("n"))
    least = max(LEAST_DOCS, share * docs.select(F.lit(1)).count())
    bit = _bit(F.col("w"))
    pages = held.where(F.col("n") >= least).groupBy(F.shiftright(bit, 15).alias("page")).agg(F.bitmap_construct_agg(bit.bitwiseAND(32767)).alias("bits"))
    out = bytearray(WORD_BITS // 8)
    for page, bits in pages.collect():  # at most WORD_BITS / 32768 rows
        out[page * 4096 : (page + 1) * 4096] = bits
    return bytes(out)


def _bit(word):
    return F.xxhash64(word).bitwiseAND(F.lit(WORD_BITS - 1).cast("long"))


def _covered(cand, words: bytes | None):
    """Letters of cand in runs that are words of the dictionary."""
    if words is None:
        return F.lit(0)

    def known(run):
        place = _bit(F.lower(run))
        byte = F.conv(F.hex(F.substring(F.lit(words), F.shiftright(place, 3).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
        return F.call_function("getbit", byte, place.bitwiseAND(7).cast("int")) == 1

    runs = F.regexp_extract_all(cand, F.lit(r"(\p{Lu}?\p{Ll}{3,}|\p{Lu}{4,})"), F.lit(1))
    return F.aggregate(F.filter(runs, known), F.lit(0), lambda n, r: n + F.length(r))


def features(cand, before, before2, token, after, words: bytes | None = None):
    """A struct of FEATURES; before2, before, after: the words around the whole token that holds the candidate."""
    n = F.greatest(F.length(cand), F.lit(1)).cast("double")
    name = F.concat_ws(" ", before2, before, F.substring(token, F.lit(1), F.greatest(F.instr(token, cand) - 1, F.lit(0))))
    flag = lambda c: F.coalesce(c, F.lit(False)).cast("double")
    values = [
        F.length(cand).cast("double"),
        _count(cand, "[0-9]") / n,
        _count(cand, "[A-Z]") / n,
        _count(cand, "[a-z]") / n,
        _count(cand, r"[_+/=.\-]") / n,
        _count(cand, r"[^A-Za-z0-9_+/=.\-]") / n,
        _count(cand, "(?<=[0-9])(?=[A-Za-z])|(?<=[A-Za-z])(?=[0-9])|(?<=[a-z])(?=[A-Z])") / n,
        F.size(F.array_distinct(F.split(cand, ""))).cast("double") / n,
        flag(cand.rlike("^([0-9a-f]+|[0-9A-F]+)$") & cand.rlike("[A-Fa-f]")),
        _covered(cand, words) / n,
        _count(cand, "/"),
        _count(cand, r"\."),
        flag(cand.rlike(r"\.(com|org|net|html?|js|css|png|jpe?g|py|txt|json|xml|gz|zip|pdf)$")),
        flag(cand.rlike(PREFIXES)),
        flag(name.rlike(SECRET_NAMES)),
        flag(name.rlike(OTHER_NAMES)),
        flag(name.rlike(r"[=:]\s*[\"']?$")),
        flag(token.rlike("[\"']")),
        flag(before.rlike(r"^[\p{L}]+[.,]?$")),
        flag(after.rlike(r"^[\p{L}]+[.,]?$")),
    ]
    return F.struct(*[v.alias(k) for k, v in zip(FEATURES, values)])


def _pseudo(i, salt: str, alphabet: str, length):
    """A repeatable pseudo-random string of the alphabet."""
    digits = F.sha2(F.concat_ws(":", F.lit(salt), i.cast("string")).cast("binary"), 512)
    pick = lambda j: F.substring(F.lit(alphabet), F.pmod(F.conv(F.substring(digits, (j % 62) * 2 + 1, 4), 16, 10).cast("int") + j * 7, F.lit(len(alphabet))) + 1, F.lit(1))
    return F.array_join(F.transform(F.sequence(F.lit(0), length - 1), pick), "")


def synthetic_findings(spark, rows: int = 6000) -> DataFrame:
    """(before2, before, token, after, label): bounded, made from a counter, the same every time."""
    i = F.col("id")
    hex_, base64_, digits, lower = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", "0123456789", "abcdefghijklmnopqrstuvwxyz"
    choose = lambda salt, options: F.get(F.array(*[o if not isinstance(o, str) else F.lit(o) for o in options]), F.pmod(F.xxhash64(F.lit(salt), i), F.lit(len(options))).cast("int"))
    size = F.pmod(F.xxhash64(F.lit("size"), i), F.lit(28)).cast("int") + 20
    key = choose("key", [_pseudo(i, "h", hex_, F.lit(40)), _pseudo(i, "h", hex_, F.lit(32)), _pseudo(i, "h", hex_, F.lit(64)), _pseudo(i, "b", base64_, size), F.concat(F.lit("AKIA"), F.upper(_pseudo(i, "a", lower + "234567", F.lit(16)))), F.concat(F.lit("ghp_"), _pseudo(i, "g", base64_[:62], F.lit(36)))])
    random = choose("same", [_pseudo(i, "h", hex_, F.lit(40)), _pseudo(i, "h", hex_, F.lit(32)), _pseudo(i, "h", hex_, F.lit(64)), F.upper(_pseudo(i, "h", hex_, F.lit(40)))])
    short = F.pmod(F.xxhash64(F.lit("short"), i), F.lit(9)).cast("int") + 8
    password = F.concat(_pseudo(i, "s", base64_[:62], short - 2), choose("mark", ["!", "@", "$", "%", "&", "7", "q"]), _pseudo(i, "t", base64_[:62], F.lit(2)))
    key = F.when(F.pmod(F.xxhash64(F.lit("class"), i), F.lit(3)) == 0, password).otherwise(key)
    issued = choose("issued", [F.concat(F.lit("AKIA"), F.upper(_pseudo(i, "a", lower + "234567", F.lit(16)))), F.concat(F.lit("ghp_"), _pseudo(i, "g", base64_[:62], F.lit(36))), F.concat(F.lit("sk_live_"), _pseudo(i, "k", base64_[:62], F.lit(24)))])
    plain = choose("plain", ["required", "changeme", "your-password", "example", "undefined", "string,optional", "none-given", "see-below"])
    number = choose("number", [_pseudo(i, "d", digits, F.lit(16)), _pseudo(i, "d", digits, F.lit(20)), F.concat_ws("-", _pseudo(i, "d", digits, F.lit(5)), _pseudo(i, "e", digits, F.lit(6)), _pseudo(i, "f", digits, F.lit(5)))])
    word = F.concat(_pseudo(i, "w", "aeinorst", size - 4))
    path = F.concat_ws("/", F.lit("static"), _pseudo(i, "p", lower, F.lit(7)), F.concat(_pseudo(i, "q", hex_, F.lit(12)), choose("ext", [".png", ".js", ".css", ".html"])))
    uuid = F.concat_ws("-", _pseudo(i, "u", hex_, F.lit(8)), _pseudo(i, "v", hex_, F.lit(4)), _pseudo(i, "x", hex_, F.lit(4)), _pseudo(i, "y", hex_, F.lit(12)))
    host = F.concat(_pseudo(i, "m", lower, F.lit(6)), F.lit("."), _pseudo(i, "n", lower, size - 12), choose("top", [".com", ".org", ".net"]))
    secret = F.pmod(F.xxhash64(F.lit("label"), i), F.lit(5)) < 2
    named = choose("name", ["token", "secret", "password", "api_key", "API_KEY", "access_key", "auth", "client_secret"])
    other = choose("other", ["commit", "sha256", "md5", "checksum", "etag", "uuid", "id", "build", "integrity"])
    prose = choose("prose", ["the", "of", "einer", "les", "para", "with", "from", "and"])
    shape = choose("shape", ["spaced", "colon", "joined"])
    around = lambda name, value: F.struct(
        F.when(shape == "spaced", name).otherwise(prose).alias("before2"),
        F.when(shape == "spaced", F.lit("=")).when(shape == "colon", F.concat(name, F.lit(":"))).otherwise(prose).alias("before"),
        F.when(shape == "joined", F.concat(name, F.lit('="'), value, F.lit('"'))).otherwise(F.concat(F.lit('"'), value, F.lit('"'))).alias("token"),
    )
    bare = lambda value: F.struct(prose.alias("before2"), prose.alias("before"), value.alias("token"))
    false_kind = F.pmod(F.xxhash64(F.lit("kind"), i), F.lit(10))
    unnamed = F.pmod(F.xxhash64(F.lit("unnamed"), i), F.lit(6)) == 0
    made = (
        F.when(secret & unnamed, bare(issued))
        .when(secret, around(named, key))
        .when(false_kind < 2, around(other, random))
        .when(false_kind == 2, bare(number))
        .when(false_kind == 3, bare(word))
        .when(false_kind == 4, bare(path))
        .when(false_kind == 5, around(other, uuid))
        .when(false_kind == 6, bare(host))
        .when(false_kind == 8, around(named, plain))
        .otherwise(bare(random))
    )
    return spark.range(rows).select(made.alias("m"), prose.alias("after"), secret.cast("int").alias("label")).select("m.*", "after", "label")


def _assigned(token, before, before2):
    """The value that a word gives to a secret name, or the empty string. Cheap tests come first."""
    sign = lambda c: F.endswith(c, F.lit("=")) | F.endswith(c, F.lit(":"))
    joined = F.when(F.contains(token, F.lit("=")) | F.contains(token, F.lit(":")), F.regexp_extract(token, JOINED, 2)).otherwise("")
    apart = F.when(sign(before), F.when(F.concat_ws(" ", before2, before).rlike(SECRET_NAMES + r"[\w\-]*[\"']?\s?[=:]+$"), F.regexp_extract(token, VALUE, 1)).otherwise("")).otherwise("")
    return F.rtrim(F.when(joined != "", joined).otherwise(apart), F.lit(".,;:!?"))


def _candidates(token, before, before2):
    """The strings of a word that may be secrets."""
    strings = F.when(F.length(token) >= SHORTEST, F.regexp_extract_all(token, F.lit(f"({CANDIDATE})"), F.lit(1))).otherwise(F.array().cast("array<string>"))
    long_ = F.filter(strings, lambda c: c.rlike("[0-9]") | (c.rlike("[a-z]") & c.rlike("[A-Z].*[A-Z]") & (F.length(c) >= 20)))
    return bind(_assigned(token, before, before2), lambda v: F.when(F.length(v) >= 6, F.concat(F.array(v), F.filter(long_, lambda c: ~F.contains(v, c) & ~F.contains(c, v)))).otherwise(long_))


def _in_token(token, before, before2):
    return F.coalesce(F.get(_candidates(token, before, before2), F.lit(0)), F.regexp_extract(token, f"({CANDIDATE})", 1))


class Forest:
    """A trained forest as expressions."""

    def __init__(self, trees: list, share: float, words: bytes | None = None):
        self.trees, self.share, self.words = trees, share, words

    def score(self, f):
        """Mean of the trees' shares of positive findings, from a struct of features."""
        if not self.trees:
            return F.lit(self.share)
        out = F.lit(0.0)
        for tree in self.trees:
            out = out + _as_case(tree, f)
        return out / len(self.trees)


def _as_case(node, f):
    if isinstance(node, float):
        return F.lit(node)
    name, cut, low, high = node
    return F.when(f[name] <= cut, _as_case(low, f)).otherwise(_as_case(high, f))


def fitted(findings: DataFrame, trees: int = TREES, depth: int = DEPTH, seed: int = 8, words: bytes | None = None) -> Forest:
    """Train on labelled findings (before2, before, token, after, label), with the dictionary of a corpus."""
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler

    around = [F.coalesce(F.col(c), F.lit("")) for c in ("before", "before2", "token", "after")]
    known = findings.where(F.col("label").isNotNull()).select(_in_token(around[2], around[0], around[1]).alias("cand"), *[c.alias(n) for c, n in zip(around, ("before", "before2", "token", "after"))], F.col("label").cast("double").alias("label"))
    described = known.select(features(F.col("cand"), F.col("before"), F.col("before2"), F.col("token"), F.col("after"), words).alias("f"), "label")
    n, ones = described.agg(F.count(F.lit(1)), F.coalesce(F.sum("label"), F.lit(0.0))).first()
    if not n or not 0 < ones < n:
        return Forest([], ones / n if n else 0.0, words)
    rows = VectorAssembler(inputCols=FEATURES, outputCol="x").transform(described.select("f.*", "label")).select("x", "label")
    model = RandomForestClassifier(featuresCol="x", labelCol="label", numTrees=trees, maxDepth=depth, seed=seed, maxBins=64).fit(rows)
    return Forest([_tree(t) for t in model.trees], ones / n, words)


def _tree(model):
    """Nested (feature, cut, low, high) with shares at the leaves, from a tree's nodes."""

    def read(node):
        if node.numDescendants() == 0:
            stats = list(node.impurityStats().stats())
            return float(stats[1] / sum(stats))
        split = node.split()
        return (FEATURES[split.featureIndex()], float(split.threshold()), read(node.leftChild()), read(node.rightChild()))

    return read(model._call_java("rootNode"))


FINDING = "struct<place:int,candidate:string,score:double>"


def scanned(docs: DataFrame, forest: Forest, text="text", carry=None, cutoff=CUTOFF) -> DataFrame:
    """The carried columns (all by default), findings (word number, string, score of every candidate) and secrets."""
    carry = [c for c in docs.columns if c not in ("findings", "secrets")] if carry is None else list(carry)

    def found(words):
        places = F.when(F.size(words) > 0, F.sequence(F.lit(0), F.size(words) - 1)).otherwise(F.array().cast("array<int>"))
        at = lambda i: F.coalesce(F.get(words, i), F.lit(""))
        signed = lambda c: F.endswith(c, F.lit("=")) | F.endswith(c, F.lit(":"))
        # cheap tests spare nearly all words the patterns
        some = F.filter(places, lambda i: (F.length(at(i)) >= SHORTEST) | F.contains(at(i), F.lit("=")) | F.contains(at(i), F.lit(":")) | signed(at(i - 1)))

        def of_word(i):
            return F.transform(
                _candidates(at(i), at(i - 1), at(i - 2)),
                lambda c: F.struct(
                    i.alias("place"), c.alias("candidate"),
                    bind(features(c, at(i - 1), at(i - 2), at(i), at(i + 1), forest.words), forest.score).alias("score"),
                ),
            )

        return F.flatten(F.transform(some, of_word))

    return docs.select(*carry, bind(words_of(F.col(text)), found).alias("findings")).withColumn("secrets", F.filter("findings", lambda x: x["score"] >= cutoff))


def op8_secrets(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    got = scanned(docs, fitted(synthetic_findings(spark), words=dictionary(docs)), carry=["doc_id"])
    return got.select(
        "doc_id",
        F.size("findings").cast("long").alias("n_candidates"),
        F.size("secrets").cast("long").alias("n_secrets"),
        F.coalesce(F.round(F.array_max(F.transform("findings", lambda x: x["score"])), 6), F.lit(0.0)).alias("score"),
        F.array_join(F.array_sort(F.array_distinct(F.transform("secrets", lambda x: F.substring(F.sha2(x["candidate"].cast("binary"), 256), 1, 16)))), ",").alias("secret_digests"),
    )


__all__ = ["Forest", "dictionary", "fitted", "synthetic_findings", "scanned", "op8_secrets"]
