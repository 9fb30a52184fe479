"""Secret scan: candidate strings, and a random forest that removes false positives. DataFrame expressions only.

Candidates are runs of 16 or more key characters that hold a digit, values of 8 or more characters that are assigned to a
name like password or token, and private-key headers. A forest over length, character classes and transitions, dictionary
coverage, the path (source) and the neighbouring words (four before and one behind, whole) tells secrets from hashes, ids, numbers and names. It is trained on
labelled findings that are made of hashes of row numbers, in the shapes in which such strings occur; training happens on
the driver with TRAIN rows of features, and the trees become CASE expressions over higher-order functions. Texts are
scanned where they are read: no exchange, no Python on executors.

A run with `/` or `=` inside, such as a path or an unlisted name's value, scores as much as the best of itself and its
segments of 16 or more characters that hold a digit, each judged with what stands before it.

Null or empty text: no findings. Very long texts are scanned whole. Character U+0001 counts as a space. Rows with the same
or no doc_id are scanned one by one. Without a column `source` the path features are 0. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

TRAIN, TREES, DEPTH, LEAF, THRESHOLD, REDACTED = 4000, 12, 5, 8, 0.5, "<SECRET>"

# Names of helper columns, unlikely in any table.
PARTS, SCORES, DESCRIBED, PATH = "__scan_parts__", "__scan_scores__", "__scan_features__", "__scan_path__"

# Names that hold secrets, and the patterns of candidates.
NAMES = "password|passwd|pwd|secret|api_?key|token"
ASSIGNED = rf"(?i:{NAMES})[\"']?\s*[:=]\s*[\"']?"
CANDIDATE = (
    rf"(?<![A-Za-z0-9_-])(?:[A-Za-z0-9_-]*[_-])?{ASSIGNED}[^\s\"']{{8,}}"
    r"|(?<![A-Za-z0-9_+/=-])(?=[A-Za-z_+/=-]*+[0-9])[A-Za-z0-9_+/=-]{16,}"
    r"|-----BEGIN [A-Z ]*PRIVATE KEY-----"
)
ASSIGNMENT = rf"^[A-Za-z0-9_-]*?{ASSIGNED}"
DICTIONARY = (
    "about|access|account|action|address|after|also|article|base|before|build|business|button|change|check|class|client|code|color|column|comment|company|config|content|control|country|"
    "custom|data|default|document|download|email|english|error|event|example|file|filter|first|format|from|function|general|group|header|have|height|home|html|http|icon|image|index|info|"
    "input|item|label|language|last|layout|length|level|light|link|list|local|main|manager|media|member|menu|message|method|model|module|name|news|number|object|option|order|page|param|"
    "path|people|photo|place|plugin|point|position|post|product|profile|project|public|query|release|report|request|response|result|sample|screen|script|search|section|server|service|"
    "session|simple|site|size|source|start|state|status|string|style|system|table|target|template|test|text|that|their|theme|this|time|title|type|update|user|value|version|video|view|week|"
    "width|window|with|word|work|world|year|your"
)
PAIRS = "th|he|in|er|an|re|on|at|en|nd|ti|es|or|te|of|ed|is|it|al|ar|st|to|nt|ng|se|ha|as|ou|io|le"
FEATURES = ("length", "digits", "uppers", "lowers", "signs", "transitions", "distinct", "dictionary", "pairs", "hex", "number", "uuid", "vendor", "assigned", "named", "opposed", "quoted", "placeholder", "test_path", "header")


def share(c: Column, pattern: str) -> Column:
    return F.regexp_count(c, F.lit(pattern)) / F.greatest(F.length(c), F.lit(1))


def words_before(c: Column) -> Column:
    """The last four words, whole."""
    return F.substring_index(c, " ", -5)


def describe(piece: Column, left: Column, right: Column, path: Column) -> Column:
    """Struct of the features of a candidate."""
    c = F.regexp_replace(piece, ASSIGNMENT, "")
    flag = lambda x: F.when(x, 1.0).otherwise(0.0)
    near = F.lower(left)
    values = {
        "length": F.length(c).cast("double"),
        "digits": share(c, "[0-9]"),
        "uppers": share(c, "[A-Z]"),
        "lowers": share(c, "[a-z]"),
        "signs": share(c, "[^A-Za-z0-9]"),
        "transitions": share(c, "(?<=[a-z])(?=[^a-z])|(?<=[A-Z])(?=[^A-Z])|(?<=[0-9])(?=[^0-9])|(?<=[^A-Za-z0-9])(?=[A-Za-z0-9])"),
        "distinct": F.size(F.array_distinct(F.split(c, ""))) / F.greatest(F.least(F.length(c), F.lit(64)), F.lit(1)),  # over 64 at most: there are about so many key characters
        "dictionary": 1 - F.length(F.regexp_replace(F.lower(c), DICTIONARY, "")) / F.greatest(F.length(c), F.lit(1)),
        "pairs": share(F.lower(c), f"(?={PAIRS})"),
        "hex": flag(c.rlike("^(0x)?([0-9a-f]+|[0-9A-F]+)$")),
        "number": flag(c.rlike("^[0-9_+/=-]+$")),
        "uuid": flag(c.rlike("^[0-9A-Fa-f]{8}(-[0-9A-Fa-f]{4}){3}-[0-9A-Fa-f]{12}$")),
        "vendor": flag(c.rlike("^(AKIA|ASIA|gh[pousr]_|github_pat_|sk_live_|sk-|rk_live_|xox[abprs]-|AIza|glpat-|eyJ|npm_|SG)")),
        "assigned": flag(c != piece),
        "named": flag(near.rlike(rf"({NAMES}|credential|auth|bearer|private|signature|access)[a-z_ \"':=\-]{{0,12}}$")),
        "opposed": flag(near.rlike(r"(sha-?[0-9]*|md5|commit|checksum|hash|uuid|guid|digest|integrity|revision|etag|isbn|order|phone|version|href|src|url|http)[a-z_ \"':=\-/.]{0,12}$")),
        "quoted": flag(left.rlike("[\"'`]$") & right.rlike("^[\"'`]")),
        "placeholder": flag(F.lower(c).rlike(r"x{6,}|0{8,}|1234567|abcdef|your|example|changeme|placeholder|dummy|insert")),
        "test_path": flag(F.lower(path).rlike("test|example|sample|fixture|mock|doc")),
        "header": flag(piece.startswith("-----BEGIN")),
    }
    return F.struct(*[v.alias(k) for k, v in values.items()])


def labelled_findings(spark) -> DataFrame:
    """Findings with labels: shapes of secrets and of what is mistaken for them, in usual surroundings."""
    i = F.col("id")
    h = lambda salt: F.sha2(F.concat(i.cast("string"), F.lit(salt)), 256)
    pick = lambda salt, items: F.element_at(F.array(*[F.lit(x) for x in items]), (F.pmod(F.xxhash64(i, F.lit(salt)), F.lit(len(items))) + 1).cast("int"))
    b64 = lambda salt, n: F.substring(F.base64(F.unhex(h(salt))), 1, n)
    safe = lambda salt, n: F.substring(F.translate(F.base64(F.unhex(h(salt))), "+/=", "xQ7"), 1, n)
    word = lambda salt: pick(salt, DICTIONARY.split("|"))
    secret = [F.substring(h("a"), 1, 40), F.substring(h("b"), 1, 32), h("c"), b64("d", 40), safe("e", 36), F.concat(F.lit("AKIA"), F.upper(safe("f", 16))), F.concat(F.lit("ghp_"), safe("g", 36)), F.concat(F.lit("sk_live_"), safe("h", 24)), F.concat(F.lit("xoxb-"), F.substring(F.conv(F.substring(h("i"), 1, 10), 16, 10), 1, 11), F.lit("-"), safe("j", 24)), F.concat(F.lit("eyJ"), b64("k", 41)), F.concat(F.lit("AIza"), safe("l", 35)), F.concat(word("m"), F.substring(F.conv(F.substring(h("m"), 1, 8), 16, 10), 1, 3), F.lit("!"), F.substring(h("n"), 1, 4)), F.lit("-----BEGIN RSA PRIVATE KEY-----"), F.concat(word("na"), F.pmod(i, F.lit(97)).cast("string"), word("nb"))]
    other = [F.substring(h("a"), 1, 40), h("c"), F.concat_ws("-", F.substring(h("o"), 1, 8), F.substring(h("o"), 9, 4), F.substring(h("o"), 13, 4), F.substring(h("o"), 17, 4), F.substring(h("o"), 21, 12)), F.conv(F.substring(h("p"), 1, 15), 16, 10), F.concat_ws("_", word("q"), word("r"), word("s"), F.pmod(i, F.lit(10)).cast("string")), F.concat_ws("/", word("t"), word("u"), F.concat(word("v"), F.pmod(i, F.lit(90)).cast("string"))), F.concat_ws("-", F.lit("2021"), F.lit("04"), word("w"), word("x")), F.concat(F.lit("your_api_key_here_"), F.pmod(i, F.lit(90)).cast("string")), F.concat(F.repeat(F.lit("x"), 12), F.substring(h("y"), 1, 8)), F.concat(word("z"), word("za"), word("zb"), F.pmod(i, F.lit(1000)).cast("string")), F.concat(F.repeat(F.lit("="), 18), F.pmod(i, F.lit(9)).cast("string")), F.concat(F.lit("0"), F.repeat(F.lit("0"), 15), F.pmod(i, F.lit(9)).cast("string")), F.concat_ws("-", F.substring(F.conv(F.substring(h("zc"), 1, 8), 16, 10), 1, 4), F.substring(F.conv(F.substring(h("zd"), 1, 8), 16, 10), 1, 4), F.substring(F.conv(F.substring(h("ze"), 1, 8), 16, 10), 1, 4), F.lit("0042")), F.concat_ws("-", word("zf"), word("zg"), word("zh"), F.pmod(i, F.lit(100)).cast("string"))]
    label = F.pmod(i, F.lit(2)).cast("int")
    shape = F.pmod(F.xxhash64(i, F.lit("shape")), F.lit(14))
    value = F.coalesce(*[F.when((label == 1) & (shape == k), s).when((label == 0) & (shape == k), o) for k, (s, o) in enumerate(zip(secret, other, strict=True))])
    assign = pick("as", ["token = \"", "api_key: ", "password=", "secret = '", "API_KEY=\"", "pwd: ", "access_token\": \""])
    plain = (label == 1) & shape.isin(5, 6, 7, 8, 9, 10, 12) & (F.pmod(F.xxhash64(i, F.lit("bare")), F.lit(2)) == 0)
    mistaken = (label == 0) & shape.isin(7, 8, 11) & (F.pmod(F.xxhash64(i, F.lit("bare")), F.lit(2)) == 0)
    bound = (label == 1) & ~plain & (shape != 12) | mistaken
    left = F.when(label == 1, pick("l", ["the key is ", "auth: bearer ", "export ", "", "const k = \"", " and "])).otherwise(pick("m", ["commit ", "sha256:", "md5 ", "uuid=", "the file ", " in ", "id ", "see https://example.com/", "order number ", "", "checksum: "]))
    path = F.when(F.pmod(F.xxhash64(i, F.lit("p")), F.lit(6)) == 0, F.when(label == 1, "src/app").otherwise("tests/fixture")).otherwise("src1")
    rows = spark.range(0, TRAIN, 1, 4).select(label.alias("label"), F.when(bound, F.concat(assign, value)).otherwise(value).alias("piece"), F.when(bound, F.lit(" ")).otherwise(left).alias("left"), F.when(bound, F.lit("\" ")).otherwise(F.lit(" ")).alias("right"), path.alias("path"))
    return rows.select("label", describe(F.col("piece"), F.col("left"), F.col("right"), F.col("path")).alias("f"))


def grow(x: np.ndarray, y: np.ndarray, depth: int, rng) -> tuple | float:
    """A tree: (feature, threshold, lower, upper) or a leaf's share of secrets; Gini gain over a random half of the features."""
    p = float(y.mean())
    if depth == 0 or len(y) < 2 * LEAF or p in (0.0, 1.0):
        return p
    best = (1e-9, None)
    for f in sorted(rng.choice(x.shape[1], x.shape[1] // 2, replace=False).tolist()):
        order = np.argsort(x[:, f], kind="stable")
        v, c = x[order, f], np.cumsum(y[order])
        n = np.arange(1, len(y))
        ok = (v[1:] > v[:-1]) & (n >= LEAF) & (len(y) - n >= LEAF)
        if ok.any():
            a, b = c[:-1] / n, (c[-1] - c[:-1]) / (len(y) - n)
            gain = np.where(ok, 2 * p * (1 - p) - (n * 2 * a * (1 - a) + (len(y) - n) * 2 * b * (1 - b)) / len(y), -1)
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (float(gain[k]), (f, float((v[k] + v[k + 1]) / 2)))
    if best[1] is None:
        return p
    f, t = best[1]
    low = x[:, f] <= t
    return f, t, grow(x[low], y[low], depth - 1, rng), grow(x[~low], y[~low], depth - 1, rng)


def train_forest(spark) -> list:
    rows = labelled_findings(spark).orderBy(F.xxhash64("f"), "label").collect()
    x = np.array([[r["f"][k] for k in FEATURES] for r in rows], float)
    y = np.array([r["label"] for r in rows], float)
    rng = np.random.default_rng(13)
    return [grow(x[s], y[s], DEPTH, rng) for s in (rng.integers(0, len(y), len(y)) for _ in range(TREES))]


def vote(tree, f: Column) -> Column:
    if isinstance(tree, float):
        return F.lit(tree)
    k, t, low, high = tree
    return F.when(f[FEATURES[k]] <= t, vote(low, f)).otherwise(vote(high, f))


def forest_score(forest: list, f: Column) -> Column:
    return sum((vote(t, f) for t in forest), F.lit(0.0)) / len(forest)


def with_findings(docs: DataFrame, forest: list, text: str = "text", path: str = "source") -> DataFrame:
    """Adds PARTS (plain text and candidates by turns) and SCORES (of the candidates)."""
    marked = F.regexp_replace(F.translate(F.coalesce(F.col(text).cast("string"), F.lit("")), "\x01", " "), CANDIDATE, "\x01$0\x01")
    where = F.coalesce(F.col(path).cast("string"), F.lit("")) if path in docs.columns else F.lit("")
    out = docs.withColumn(PARTS, F.split(marked, "\x01")).withColumn(PATH, where)
    places = F.when(F.size(PARTS) > 1, F.sequence(F.lit(1), F.size(PARTS) - 2, F.lit(2))).otherwise(F.array().cast("array<int>"))
    part = lambda i: F.get(F.col(PARTS), i)

    def views(i):
        """The candidate, and the segments it may hide a secret in: (piece, left, right)."""
        piece, left, right = part(i), words_before(part(i - 1)), F.substring_index(part(i + 1), " ", 2)
        view = lambda p, l: F.struct(p.alias("piece"), l.alias("left"), right.alias("right"))  # noqa: E731, E741
        inner = F.filter(F.split(piece, "[/=]+"), lambda s: (F.length(s) >= 16) & (F.length(s) < F.length(piece)) & s.rlike("[0-9]"))
        inner = F.when(piece.rlike("[/=]") & ~piece.rlike(ASSIGNMENT), inner).otherwise(F.array().cast("array<string>"))
        return F.concat(F.array(view(piece, left)), F.transform(inner, lambda s: view(s, F.concat(left, F.left(piece, F.instr(piece, s) - 1)))))

    out = out.withColumn(DESCRIBED, F.transform(places, lambda i: F.transform(views(i), lambda v: describe(v["piece"], v["left"], v["right"], F.col(PATH)))))
    return out.withColumn(SCORES, F.transform(DESCRIBED, lambda seen: F.array_max(F.transform(seen, lambda f: forest_score(forest, f))))).drop(DESCRIBED, PATH)


def scan_secrets(docs: DataFrame) -> DataFrame:
    """A row for each candidate: doc_id, finding (from 0), start and length in characters, its digest, masked form, score, secret."""
    found = with_findings(docs, train_forest(docs.sparkSession))
    # posexplode_outer: for the inner form the optimizer adds a filter that would mark and score every text once more
    rows = found.select(F.col("doc_id").cast("long").alias("doc_id"), F.monotonically_increasing_id().alias("row"), F.posexplode_outer(F.transform(SCORES, lambda s, i: F.struct(F.get(F.col(PARTS), 2 * i + 1).alias("piece"), F.length(F.get(F.col(PARTS), 2 * i)).alias("gap"), s.alias("score")))).alias("finding", "f")).filter("f IS NOT NULL")
    before = Window.partitionBy("row").orderBy("finding").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    piece = F.col("f.piece")
    value = F.regexp_replace(piece, ASSIGNMENT, "")
    rows = rows.withColumn("end", F.sum((F.col("f.gap") + F.length(piece)).cast("long")).over(before))
    return rows.select("doc_id", "finding", (F.col("end") - F.length(value)).alias("start"), F.length(value).cast("long").alias("length"), F.sha2(value, 256).alias("digest"), F.concat(F.left(value, F.lit(4)), F.lit("...")).alias("masked"), F.round("f.score", 6).alias("score"), (F.col("f.score") >= THRESHOLD).alias("secret"))


def redact(docs: DataFrame) -> DataFrame:
    """The documents with their secrets replaced in `text`; the names they are assigned to stay. n_chars follows a changed text; other columns stay."""
    found = with_findings(docs, train_forest(docs.sparkSession))
    clean = lambda p: F.concat(F.regexp_extract(p, ASSIGNMENT, 0), F.lit(REDACTED))
    secret = lambda i: (i % 2 == 1) & (F.get(F.col(SCORES), F.floor(i / 2).cast("int")) >= THRESHOLD)
    text = F.array_join(F.transform(PARTS, lambda p, i: F.when(secret(i), clean(p)).otherwise(p)), "")
    out = found.withColumn(PATH, F.when(F.exists(SCORES, lambda s: s >= THRESHOLD), text))
    out = out.withColumn("text", F.coalesce(PATH, "text"))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col(PATH).isNotNull(), F.length(PATH).cast(dict(docs.dtypes)["n_chars"])).otherwise(F.col("n_chars")))
    return out.select(*docs.columns)


def op10_forest_secret_scan(spark, sf_dir: str) -> DataFrame:
    return scan_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet"))
