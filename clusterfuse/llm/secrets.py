"""Secret scanning: candidates by pattern, false positives removed by a random forest.

A candidate is a run of at least 16 key characters with a digit in it, a known key prefix with 12 or more key characters,
a value of 8 or more characters that is quoted or assigned after a secret word, or the password of a connection string.
Its features are length, character classes and
transitions between them, distinct characters, dictionary coverage, path signs and the words around it. The forest is
trained on labelled findings (texts with their verdict); without a table of those, ``labelled_findings`` makes a set of
known formats and look-alikes by rule. The trees are emitted as conditional expressions, so a scan is one projection in
the JVM without a shuffle.

Null and empty texts have no candidates. Every place of a candidate is scored with its own neighbours; a string
that stands in a text several times is one finding, at its first place with the best score, and if that passes all its
places are redacted. Repeated rows are scanned one by one; an empty table gives an empty result.
Columns other than doc_id and text pass through ``redacted`` unchanged, whatever their names.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import struct_of
from .common import let, table, unused

#: What may stand before a candidate: a secret word with a sign or a quote, or the user of a connection string.
_WORD = r"(?i:token|secret|passw(?:or)?d|passphrase|pwd|api[_.-]?key|access[_.-]?key|auth|credential|private[_.-]?key|bearer)[A-Za-z0-9_-]{0,16}+[\"']?"
_QUOTED = _WORD + r"[ \t]{0,3}(?:=>|:=|[=:])?[ \t]{0,3}[\"'](?=[^\s\"']{8})"
_ASSIGNED = _WORD + r"[ \t]{0,3}(?:=>|:=|[=:])[ \t]{0,3}(?=[^\s\"'`<>,;(){}\[\]]{8})"
_LOGIN = r"://[^\s/:@\"'<>]{0,64}:(?=[^\s/\"'<>]{8,256}@)"
_VALUES = [
    (_LOGIN, r"[^\s/\"'<>]{8,256}(?=@)"),
    (_QUOTED, r"[^\s\"']{8,}+"),
    (_ASSIGNED, r"[^\s\"'`<>,;(){}\[\]]{7,}[^\s\"'`<>,;(){}\[\].:]"),
    (r"(?<![A-Za-z0-9_/+=-])", r"(?:AKIA|ASIA|ghp_|gho_|ghs_|github_pat_|xox[abp]-|sk_live_|rk_live_|sk-|AIza|glpat-|npm_|eyJ)[A-Za-z0-9_/+=-]{12,}+"),
    (r"(?<![A-Za-z0-9_/+=-])", r"(?=[A-Za-z_/+=-]*[0-9])[A-Za-z0-9_/+=-]{16,}+"),
]
CANDIDATE = "|".join(f"(?:{before}{value})" for before, value in _VALUES)
# What a text must hold somewhere if it has a candidate; compound names need "key" besides.
MARKS = ["token", "secret", "passw", "passphrase", "pwd", "auth", "credential", "bearer"]
KEYED = ["api", "access", "private"]
PREFIXES = ["AKIA", "ASIA", "ghp_", "gho_", "ghs_", "github_pat_", "xox", "sk_live_", "rk_live_", "sk-", "AIza", "glpat-", "npm_", "eyJ"]
#: What stands before the value in a match of CANDIDATE.
LEAD = f"^(?:{_LOGIN.partition('(?=')[0]}|{_QUOTED}|{_ASSIGNED})"
#: Labelled findings that a forest is trained on, at most.
MAX_LABELLED = 4000
TREES, DEPTH, LEAST = 12, 6, 8
CUT = 0.5
BEFORE, AFTER = 48, 8
MASK = "[SECRET]"
# Common parts of names, paths and placeholders.
DICTIONARY = "test example sample dummy placeholder user name data file path page index image temp local python java node module class public private static version release build candidate config package dist article title post long handler service client server get set by for from with the and your here change lib src main http www com org key token value xxxx 0000 1234 abcd"
SECRET_NEAR = r"(token|secret|passw|pwd|api.?key|access.?key|auth|credential|private|bearer)[^\n]{0,16}$"
HASH_NEAR = r"(sha-?\d*|md5|commit|checksum|digest|hash|revision|uuid|guid|etag|integrity|blob|tree)[^\n]{0,16}$"
KNOWN = r"^(AKIA|ASIA|ghp_|gho_|ghs_|github_pat_|xox[abp]-|sk_live_|rk_live_|sk-|AIza|glpat-|npm_|eyJ)"
FEATURES = ["length", "digits", "upper", "lower", "transitions", "distinct", "hexadecimal", "coverage", "slashes", "joints", "path", "secret_near", "hash_near", "assigned", "quoted", "known", "all_digits", "run", "symbols", "consonants", "code", "login"]


def _features(c: Column, b: Column, a: Column) -> list[Column]:
    """FEATURES of candidate ``c`` with the text right before and after it."""
    n = F.char_length(c).cast("double")
    share = lambda pattern: F.regexp_count(c, F.lit(pattern)) / n
    flag = lambda x: x.cast("double")
    low = F.lower(b)
    words = "|".join(sorted(DICTIONARY.split(), key=len, reverse=True))
    out = [
        n,
        share("[0-9]"),
        share("[A-Z]"),
        share("[a-z]"),
        share(r"(?<=[0-9])(?=[A-Za-z])|(?<=[A-Za-z])(?=[0-9])|(?<=[a-z])(?=[A-Z])|(?<=[A-Z])(?=[a-z])"),
        F.size(F.array_distinct(F.split(c, ""))) / n,
        flag(c.rlike(r"^[0-9a-fA-F]+$")),
        1 - F.char_length(F.regexp_replace(F.lower(c), f"({words})", "")) / n,
        share("/"),
        share("[_-]"),
        flag(b.rlike(r"(://\S*|[/.])$") | a.rlike(r"^[./]\w")),
        flag(low.rlike(SECRET_NEAR)),
        flag(low.rlike(HASH_NEAR)),
        flag(b.rlike(r"[=:]\s*[\"']?$")),
        flag(b.rlike(r"[\"']$") & a.rlike(r"^[\"']")),
        flag(c.rlike(KNOWN)),
        flag(c.rlike(r"^[0-9]+$")),
        share(r"(.)\1\1"),
        share("[^A-Za-z0-9_/+=-]"),
        share("(?i)[bcdfghjklmnpqrstvwxz]{4}"),
        flag(c.rlike(r"^[$%]|^[a-z_]+(?:[.][A-Za-z_]+)+$|://")),
        flag(b.rlike(r"://[^\s/:@]*:$") & a.startswith("@")),
    ]
    return [x.cast("double").alias(f) for f, x in zip(FEATURES, out)]


def may_hold(text: Column) -> Column:
    """False only where no alternative of CANDIDATE can match: plain searches, which spare most texts the pattern."""
    some = lambda t, words: reduce(lambda a, b: a | b, [F.contains(t, F.lit(w)) for w in words])
    run = text.rlike("[0-9]") & text.rlike("[A-Za-z0-9_/+=-]{16}")
    return F.contains(text, F.lit("://")) | run | some(text, PREFIXES) | let(F.lower(text), lambda low: some(low, MARKS) | (F.contains(low, F.lit("key")) & some(low, KEYED)))


def candidates(text: Column) -> Column:
    """Array of (value, start, x) of all places of candidates; start counts characters from 1, x holds the features."""

    def placed(gaps: Column, found: Column) -> Column:
        """Each match with its place and the text around it, from the matches and what stands between them."""

        def piece(g: Column, f: Column) -> Column:
            return F.struct(g.alias("gap"), f.alias("match"), F.regexp_extract(f, LEAD, 0).alias("lead"))

        pieces = F.zip_with(F.slice(gaps, F.lit(1), F.size(found)), found, piece)
        after = F.transform(found, lambda f, i: F.substring(F.concat(F.get(gaps, i + 1), F.coalesce(F.get(found, i + 1), F.lit(""))), 1, AFTER))
        start = F.struct(F.lit(0).alias("pos"), F.lit("").alias("tail"), F.array().cast("array<struct<value:string,start:int,b:string,a:string>>").alias("out"))

        def step(acc: Column, x: Column) -> Column:
            p = x["piece"]
            skip = F.char_length(p["lead"])
            entry = F.struct(
                F.substr(p["match"], skip + 1).alias("value"),
                (acc["pos"] + F.char_length(p["gap"]) + skip + 1).alias("start"),
                F.right(F.concat(acc["tail"], p["gap"], p["lead"]), F.lit(BEFORE)).alias("b"),
                x["a"].alias("a"),
            )
            return F.struct(
                (acc["pos"] + F.char_length(p["gap"]) + F.char_length(p["match"])).alias("pos"),
                F.right(F.concat(acc["tail"], p["gap"], p["match"]), F.lit(BEFORE)).alias("tail"),
                F.concat(acc["out"], F.array(entry)).alias("out"),
            )

        return F.aggregate(F.zip_with(pieces, after, lambda p, a: F.struct(p.alias("piece"), a.alias("a"))), start, step, lambda acc: acc["out"])

    def one(c: Column) -> Column:
        return F.struct(c["value"].alias("value"), c["start"].alias("start"), F.struct(*_features(c["value"], c["b"], c["a"])).alias("x"))

    def described(t: Column) -> Column:
        cut = F.struct(F.split(t, CANDIDATE, -1).alias("gaps"), F.regexp_extract_all(t, F.lit(CANDIDATE), F.lit(0)).alias("found"))
        return let(cut, lambda x: F.transform(placed(x["gaps"], x["found"]), one))

    return let(F.when(may_hold(text), text).otherwise(""), described)


def labelled_findings(spark: SparkSession, rows: int = MAX_LABELLED) -> DataFrame:
    """Labelled findings by rule: text, secret (0 or 1). Formats of keys against digests, numbers, names, paths and placeholders."""
    i = F.col("id").cast("string")
    sha = F.sha1(F.concat(F.lit("k"), i).cast("binary"))
    long_ = F.sha2(F.concat(F.lit("l"), i).cast("binary"), 512)
    b64 = F.regexp_replace(F.base64(F.unhex(long_)), r"\s", "")
    plain = F.regexp_replace(b64, "[+/=]", "")
    b32 = F.translate(F.upper(long_), "0189", "GHJK")
    pick = lambda values, salt: F.element_at(F.array(*[F.lit(v) for v in values]), (F.pmod(F.xxhash64(F.col("id"), F.lit(salt)), F.lit(len(values))) + 1).cast("int"))
    filler = pick(["the host of ", "In der Regel ", "and then ", "", "pour la ", "see also ", "que los ", "x: "], 1)
    sign = pick([' = "', ": ", "=", ' : "', " => '"], 2)
    close = F.when(F.contains(sign, F.lit('"')), '"').when(F.contains(sign, F.lit("'")), "'").otherwise("")
    said = pick(["token", "TOKEN", "secret", "api_key", "apiKey", "password", "access_key", "auth_token", "client_secret"], 3)
    word = lambda s: pick(["user", "name", "page", "index", "image", "config", "module", "article", "release", "package"], s)
    number = F.conv(F.substring(sha, 1, 4), 16, 10)
    letters = F.translate(F.upper(long_), "0123456789", "QRSTUVWXYZ")
    strong = F.concat(F.substring(plain, 5, 5), pick([".", "!", "@", "$", ":", "#"], 32), F.substring(plain, 12, 4), pick(["!", "", ".x", "$9", "@q"], 33))
    prose = pick("required everything undefined expired mandatory generated documentation forgotten available important published information registration something authentication tomorrow erforderlich verschiedene necesario importante seulement toujours disponible".split(), 34)
    text = (
        F.when(F.col("kind") == 0, F.concat(said, sign, sha, close))
        .when(F.col("kind") == 1, F.concat(pick(["aws ", "key: ", "AWS_ACCESS_KEY_ID="], 4), F.lit("AKIA"), F.substring(b32, 1, 16)))
        .when(F.col("kind") == 2, F.concat(pick(["", "use ", "token: "], 5), pick(["ghp_", "gho_", "sk_live_", "glpat-", "npm_"], 6), F.substring(plain, 1, 36)))
        .when(F.col("kind") == 3, F.concat(said, sign, F.substring(b64, 1, 40), close))
        .when(F.col("kind") == 4, F.concat(said, sign, F.substring(plain, 1, 22), close))
        .when(F.col("kind") == 5, F.concat(said, sign, F.substring(long_, 1, 32), close))
        .when(F.col("kind") == 6, F.concat(pick(["commit ", "blob ", "revision ", "tree "], 7), sha))
        .when(F.col("kind") == 7, F.concat(pick(["sha256:", "sha256 = ", "md5: ", "checksum: ", "digest="], 8), F.when(F.col("id") % 2 == 0, F.substring(long_, 1, 64)).otherwise(F.substring(long_, 1, 32))))
        .when(F.col("kind") == 8, F.concat(pick(["uuid ", "id: ", "guid=", "request "], 9), F.concat_ws("-", F.substring(sha, 1, 8), F.substring(sha, 9, 4), F.substring(sha, 13, 4), F.substring(sha, 17, 4), F.substring(sha, 21, 12))))
        .when(F.col("kind") == 9, F.concat(pick(["paid with ", "", "card: ", "number ", "account = "], 10), F.substring(F.translate(long_, "abcdef", "123456"), 1, 16)))
        .when(F.col("kind") == 10, F.concat(F.lit("/usr/lib/python3/"), word(11), F.lit("/"), word(12), F.lit("_"), number, F.lit("/"), word(13)))
        .when(F.col("kind") == 11, F.concat(F.lit("get_"), word(14), F.lit("_by_"), word(15), F.lit("_v"), number))
        .when(F.col("kind") == 12, F.concat(F.lit("https://www.example.com/2021/"), word(16), F.lit("-for-the-"), word(17), F.lit("-"), number))
        .when(F.col("kind") == 13, F.concat(said, sign, pick(["your-api-key-here-0000", "xxxxxxxxxxxxxxxxxxxx0000", "EXAMPLE_TOKEN_1234567890", "test-token-placeholder-1", "change_me_please_1234", "0000000000000000"], 18), close))
        .when(F.col("kind") == 14, F.concat(word(19), F.lit("-release-build-"), number, F.lit("-"), word(20)))
        .when(F.col("kind") == 15, F.concat(F.lit('integrity="sha512-'), b64, F.lit('"')))
        .when(F.col("kind") == 16, F.concat(pick(["aws ", "key: ", "AWS_ACCESS_KEY_ID="], 4), F.lit("AKIA"), F.substring(letters, 1, 16)))
        .when(F.col("kind") == 17, F.concat(said, sign, strong, close))
        .when(F.col("kind") == 18, F.concat(said, sign, F.substring(F.regexp_replace(plain, "[0-9]", ""), 1, 24), close))
        .when(F.col("kind") == 19, F.concat(pick(["postgres://", "mysql://", "amqp://", "redis://"], 22), word(23), F.lit(":"), strong, F.lit("@db.internal/x")))
        .when(F.col("kind") == 20, F.concat(said, sign, F.substring(plain, 1, 11), close))
        .when(F.col("kind") == 21, F.concat(said, sign, prose, close))
        .when(F.col("kind") == 22, F.concat(said, sign, pick(["config.", "os.environ.", "self.", "settings.", "process.env."], 24), word(25), F.lit("_"), word(26), close))
        .when(F.col("kind") == 23, F.concat(said, sign, pick(["${", "$", "%", "https://example.com/"], 27), word(28), F.lit("_"), word(29), close))
        .when(F.col("kind") == 24, F.concat(F.lit("http://localhost:"), number, F.lit("/"), word(30), F.lit(" and "), said, F.lit(" "), prose))
        .otherwise(F.concat(said, sign, word(31), F.lit("-"), prose, close))
    )
    # 11 of 26 kinds are secrets
    return spark.range(rows).withColumn("kind", F.pmod(F.col("id"), F.lit(26))).select(F.concat(filler, text, pick([".", " and so on", "", ", he said", "\n"], 21)).alias("text"), ((F.col("kind") < 6) | F.col("kind").between(16, 20)).cast("int").alias("secret"))


class Tree:
    """A node: leaf probability, or feature, cut and two nodes."""

    def __init__(self, x: np.ndarray, y: np.ndarray, rng: np.random.Generator, depth: int):
        self.value, self.feature = float(y.mean()), None
        if depth == 0 or len(y) < 2 * LEAST or self.value in (0.0, 1.0):
            return
        best = (1e-9, None, 0.0)
        impurity = self.value * (1 - self.value)
        for f in rng.choice(x.shape[1], size=6, replace=False):
            order = np.argsort(x[:, f], kind="stable")
            v, t = x[order, f], np.cumsum(y[order])
            at = np.flatnonzero(v[1:] > v[:-1])
            at = at[(at + 1 >= LEAST) & (len(y) - at - 1 >= LEAST)]
            if len(at):
                left, right = at + 1.0, len(y) - at - 1.0
                p, q = t[at] / left, (t[-1] - t[at]) / right
                gain = impurity - (left * p * (1 - p) + right * q * (1 - q)) / len(y)
                k = int(np.argmax(gain))
                if gain[k] > best[0]:
                    best = (gain[k], int(f), float((v[at[k]] + v[at[k] + 1]) / 2))
        if best[1] is not None:
            self.feature, self.cut = best[1], best[2]
            side = x[:, self.feature] <= self.cut
            self.low, self.high = Tree(x[side], y[side], rng, depth - 1), Tree(x[~side], y[~side], rng, depth - 1)

    def column(self, x: Column) -> Column:
        if self.feature is None:
            return F.lit(round(self.value, 6))
        return F.when(x[FEATURES[self.feature]] <= self.cut, self.low.column(x)).otherwise(self.high.column(x))


def train(findings: DataFrame, limit: int = MAX_LABELLED, seed: int = 11) -> list[Tree]:
    """Forest from labelled findings (text, secret), at most ``limit`` of them, first by hash of the text."""
    sample = findings.filter(F.col("text").isNotNull() & F.col("secret").isNotNull()).orderBy(F.xxhash64("text"), "text", "secret").limit(limit)
    rows = sample.select("secret", F.explode(candidates(F.col("text"))).alias("c")).select("secret", "c.x.*").collect()
    if not rows:
        return []
    rows.sort()
    x, y = np.array([[r[f] for f in FEATURES] for r in rows]), np.array([float(r["secret"]) for r in rows])
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(TREES):
        drawn = rng.integers(0, len(y), len(y))
        out.append(Tree(x[drawn], y[drawn], rng, DEPTH))
    return out


def score_column(forest: list[Tree], x: Column) -> Column:
    total = F.lit(0.0)
    for tree in forest:
        total = total + tree.column(x)
    return F.round(total / max(len(forest), 1), 6)


def findings_column(text: Column, forest: list[Tree]) -> Column:
    """Array of (value, start, score) of the distinct candidates, each at its first place with the best score."""
    places = F.transform(candidates(text), lambda c: F.struct(c["value"].alias("value"), (-score_column(forest, c["x"])).alias("low"), c["start"].alias("start")))
    first = let(F.array_sort(places), lambda p: F.filter(p, lambda c, i: (i == 0) | (F.get(p, i - 1)["value"] != c["value"])))
    ordered = F.array_sort(F.transform(first, lambda c: F.struct(c["start"].alias("start"), c["value"].alias("value"), c["low"].alias("low"))))
    return F.transform(ordered, lambda c: F.struct(c["value"].alias("value"), c["start"].alias("start"), (-c["low"]).alias("score")))


def scan(text: Column, forest: list[Tree], cut: float = CUT) -> Column:
    """A struct: n_candidates, and secrets, an array of (value, start, score) from ``cut`` on."""
    return let(findings_column(text, forest), lambda f: struct_of(n_candidates=F.size(f).cast("long"), secrets=F.filter(f, lambda c: c["score"] >= cut)))


def scanned(docs: DataFrame, forest: list[Tree], cut: float = CUT, name: str = "scan") -> DataFrame:
    """``docs`` with one more column ``name``, the scan; a caller's column of that name is an error, not overwritten."""
    if unused(docs.columns, name) != name:
        raise ValueError(f"there is a column {name} already")
    return docs.withColumn(name, scan(F.col("text"), forest, cut))


def redacted(docs: DataFrame, forest: list[Tree], cut: float = CUT) -> DataFrame:
    """All rows with the caller's columns alone: every secret of ``text`` is masked, and n_chars, if there is one, counted anew where a text changed."""
    name = unused(docs.columns, "redacted")

    def masked(f: Column) -> Column:
        return F.when(F.size(f["secrets"]) > 0, redacted_text(F.col("text"), f["secrets"]))

    out = docs.withColumn(name, let(scan(F.col("text"), forest, cut), masked))
    n_chars = F.when(F.col(name).isNotNull(), F.char_length(name))
    new = {"text": F.coalesce(name, "text")} | ({"n_chars": F.coalesce(n_chars.cast(dict(docs.dtypes)["n_chars"]), F.col("n_chars"))} if "n_chars" in docs.columns else {})
    return out.select(*[new[c].alias(c) if c in new else F.col(f"`{c}`") for c in docs.columns])


def redacted_text(text: Column, secrets: Column) -> Column:
    """Text with every place of every secret replaced, long ones first; null stays null."""
    ordered = F.array_sort(secrets, lambda a, b: F.char_length(b["value"]) - F.char_length(a["value"]))
    return F.aggregate(ordered, text, lambda t, s: F.replace(t, s["value"], F.lit(MASK)))


def query(spark, sf_dir):
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    out = scanned(docs, train(labelled_findings(spark)))
    s = F.col("scan.secrets")
    return out.select(
        "doc_id",
        "scan.n_candidates",
        F.size(s).cast("long").alias("n_secrets"),
        F.coalesce(F.array_max(F.transform(s, lambda x: x["score"])), F.lit(0.0)).alias("score"),
        F.transform(s, lambda x: F.struct(x["start"].alias("start"), F.char_length(x["value"]).alias("length"), F.sha2(x["value"].cast("binary"), 256).alias("sha256"), x["score"].alias("score"))).alias("secrets"),
        F.sha2(F.coalesce(redacted_text(F.col("text"), s), F.lit("")).cast("binary"), 256).alias("redacted_sha256"),
    )
