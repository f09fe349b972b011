"""Secret scan: token-shaped candidates, false positives removed by a random forest. DataFrame functions only.

A regular expression names the candidates of a text; the text around them comes from splitting at the same expression. Each
candidate becomes a row of numbers: length, transitions between kinds of characters, distinct characters, coverage by
dictionary words, place in a path, and the words before it. A random forest trained on labelled findings scores it. The
forest is compiled to one SQL expression, so candidates are scored, and secrets blanked out, inside their row: no shuffle and
no join, whatever the skew.

Edges: null and empty texts have no candidates and stay as they are; repeated rows and repeated candidates are judged one by
one; a text of any length is scanned whole; an empty table gives no rows; a null id stays null.
"""

from __future__ import annotations

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

CANDIDATE = r"[A-Za-z0-9+/=_\-]{16,}"
BLANK = "[SECRET]"
# Words whose letters speak against a random token, and words that stand before secrets or before harmless ids.
DICTIONARY = (
    "about above access account action address after again algorithm allow also application array author available back base before begin between block body branch build button cache call change channel char check "
    "child class clear client close code column commit common compare component config connect constant container content context control copy count create current data database date debug default define delete "
    "description design detail device directory display document domain download driver element email empty enable engine entry error event example exception execute export extension external factory false feature "
    "field file filter find first float folder form format frame from function general generate global graph group handle hash header height history host image import include index info init input insert instance "
    "integer interface internal item java label language last layer layout length level library license limit line link list load local location login main manager matrix memory menu message method model module "
    "name network node normal number object offset open option order other output owner package page panel parameter parent parse password path pattern payload permission person point policy port position press "
    "print private process product profile project property protocol provider public query queue random range read record reference region register release remote remove render report request reset resource response "
    "result return role root route rule sample schema scope script search secret section security select send sequence server service session setting shape share simple single size sort source spec stack start state "
    "static status step stop storage store stream string struct style submit summary support switch symbol sync system table target task template test text thread time title token tool total track transfer transform "
    "tree trigger true type undefined unique unit update upload user util valid value variable vector version view visible warning water while widget width window with word worker world write"
).split()
NEAR_SECRET = r"(token|secret|passw(or)?d|pwd|api.?key|apikey|access.?key|auth|bearer|credential|private.?key)\W{0,4}\w{0,12}\W{0,6}$"
NEAR_HARMLESS = r"(sha\d*|md5|commit|checksum|digest|uuid|guid|revision|etag|build|example|sample|placeholder|hash|integrity|trace|request.?id)\W{0,4}\w{0,12}\W{0,6}$"
FEATURES = ("length", "transitions", "distinct", "digits", "uppers", "vowels", "coverage", "hexadecimal", "uuid", "path", "slashes", "near_secret", "near_harmless", "assigned", "quoted")


def _share(text: Column, pattern: str, size: Column) -> Column:
    """Share of the characters that the pattern matches."""
    return (size - F.length(F.regexp_replace(text, pattern, ""))) / size


def features(token: Column, before: Column, after: Column) -> Column:
    """A struct of doubles in the order of FEATURES."""
    size = F.length(token).cast("double")
    kinds = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(token, "[a-z]+", "a"), "[A-Z]+", "B"), "[0-9]+", "1"), r"[^aB1]+", "-")
    plain, near = F.lower(token), F.lower(before)
    words = "|".join(sorted((w for w in DICTIONARY if len(w) >= 4), key=lambda w: (-len(w), w)))
    flag = lambda c: c.cast("double")
    values = (
        size,
        (F.length(kinds) - 1) / size,
        F.size(F.array_distinct(F.split(token, ""))) / size,
        _share(token, "[0-9]", size),
        _share(token, "[A-Z]", size),
        _share(plain, "[aeiou]", size),
        _share(plain, words, size),
        flag(token.rlike("^[0-9a-fA-F]+$")),
        flag(token.rlike("^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$")),
        flag(before.rlike(r"([/\\.~]|://\S*)$") | after.rlike(r"^(\.[a-z]{1,5}\b|[/\\])")),
        _share(token, "/", size),
        flag(near.rlike(NEAR_SECRET)),
        flag(near.rlike(NEAR_HARMLESS)),
        flag(before.rlike(r"[=:]\s*[\"'`]?$")),
        flag(before.rlike(r"[\"'`]$") & after.rlike(r"^[\"'`]")),
    )
    return F.struct(*(v.alias(n) for v, n in zip(values, FEATURES)))


def candidates(text: Column) -> Column:
    """Array of (token, before, after) of the candidates that hold a digit or both cases, in their order."""
    found = F.regexp_extract_all(text, F.lit(CANDIDATE), F.lit(0))
    between = F.split(text, CANDIDATE, -1)
    rows = F.transform(found, lambda t, i: F.struct(t.alias("token"), F.right(F.element_at(between, i + 1), F.lit(48)).alias("before"), F.left(F.element_at(between, i + 2), F.lit(16)).alias("after")))
    return F.filter(rows, lambda r: r["token"].rlike("[0-9]") | (r["token"].rlike("[a-z][A-Z]") & r["token"].rlike("[A-Z].*[A-Z]")))


def labelled_findings(spark: SparkSession, n: int = 6000, first: int = 0) -> DataFrame:
    """n labelled findings (token, before, after, label), written by rule: half secrets, half what only looks like one. A finding
    follows from its number; those from `first` on have other tokens than those before."""
    r = lambda salt: F.pmod(F.xxhash64("id", F.lit(salt)), F.lit(1 << 30)).cast("int")
    pick = lambda salt, *choices: F.element_at(F.array(*(c if isinstance(c, Column) else F.lit(c) for c in choices)), r(salt) % len(choices) + 1)
    hexa = lambda salt: F.sha2(F.concat(F.col("id"), F.lit(salt)), 256)
    base = lambda salt: F.regexp_replace(F.base64(F.unhex(F.concat(hexa(salt), hexa(salt + "+")))), "[+/=]", "")
    word = lambda salt: pick(salt, *DICTIONARY[:: max(1, len(DICTIONARY) // 90)])
    size = F.lit(20) + r("size") % 29
    secret = pick("kind", F.left(hexa("a"), F.lit(40)), F.left(hexa("b"), F.lit(32)), F.left(base("c"), size), F.concat(pick("tag", "sk_live_", "ghp_", "AKIA", "xoxb-", ""), F.left(base("d"), size)), hexa("e"))
    uuid = F.regexp_replace(F.left(hexa("f"), F.lit(32)), "^(.{8})(.{4})(.{4})(.{4})(.{12})$", "$1-$2-$3-$4-$5")
    camel = F.concat(word("w1"), F.initcap(word("w2")), F.initcap(word("w3")), F.initcap(word("w4")), (r("no") % 90).cast("string"))
    snake = F.translate(F.concat_ws(" ", word("w5"), word("w6"), word("w7"), word("w8"), (r("no") % 900).cast("string")), " ", "_")
    snake = F.when(r("join") % 3 == 0, F.replace(snake, F.lit("_"), F.lit("-"))).when(r("join") % 3 == 1, F.replace(snake, F.lit("_"), F.lit("/"))).otherwise(snake)
    harmless = pick("sham", uuid, camel, snake, F.left(hexa("g"), F.lit(40)), hexa("h"), F.lpad((r("num").cast("long") * 7919).cast("string"), 16, "4"), F.repeat(pick("rep", "0", "x1", "ab0"), 16 + r("size") % 9), F.concat(word("w1"), F.lit("/"), word("w2"), F.lit("/"), F.left(hexa("i"), F.lit(20))))
    before = F.concat_ws(" ", word("v1"), word("v2"), pick("near", 'token = "', "token: ", "api_key='", "secret=", "password: ", 'access_key = "', "Authorization: Bearer ", "auth_token = '"))
    calm = F.concat_ws(" ", word("v1"), word("v2"), pick("near", "commit ", "sha256: ", "in ", "the ", 'id = "', "checksum=", "https://host.example/", "see /usr/share/", "uuid: ", "md5 ", "import ", "(", ""))
    after = F.concat(F.regexp_extract(F.col("before"), "[\"']$", 0), F.lit(" "), word("v3"))
    # a tenth of the secrets stand in calm surroundings, a tenth of the sham ones behind a secret's name but with a word's or number's form
    odd = r("odd") % 10 == 0
    rows = spark.range(first, first + n, 1, 2).withColumn("label", (F.col("id") % 2).cast("double"))
    form = pick("sham2", camel, snake, F.repeat(pick("rep", "0", "x1", "ab0"), 16 + r("size") % 9), F.lit("your_token_goes_here_123"), F.lit("XXXXXXXXXXXXXXXX0000"))
    rows = rows.withColumn("token", F.when(F.col("label") == 1, F.when(odd, F.left(base("c"), size)).otherwise(secret)).when(odd, form).otherwise(harmless))
    rows = rows.withColumn("before", F.when((F.col("label") == 1) != odd, before).otherwise(calm))
    return rows.select("token", "before", after.alias("after"), "label")


def _tree(node, row) -> Column:
    """One tree as nested conditions; a leaf gives its share of secrets."""
    if node.getClass().getSimpleName() == "LeafNode":
        harmless, secret = list(node.impurityStats().stats())
        return F.lit(float(secret) / max(float(secret) + float(harmless), 1e-9))
    split = node.split()
    return F.when(row[FEATURES[split.featureIndex()]] <= float(split.threshold()), _tree(node.leftChild(), row)).otherwise(_tree(node.rightChild(), row))


class Forest:
    """A random forest over FEATURES as a function from a feature struct to the probability of a secret."""

    def __init__(self, findings: DataFrame, trees: int = 15, depth: int = 6, seed: int = 11):
        """findings: (token, before, after, label); a bounded training set."""
        rows = findings.select(features(F.col("token"), F.col("before"), F.col("after")).alias("f"), "label").select("f.*", "label")
        table = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(rows).select("features", "label")
        self.model = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="sqrt").fit(table)
        self.roots = [t._java_obj.rootNode() if hasattr(t, "_java_obj") else t._call_java("rootNode") for t in self.model.trees]

    def __call__(self, row: Column) -> Column:
        total = None
        for root in self.roots:
            total = _tree(root, row) if total is None else total + _tree(root, row)
        return total / len(self.roots)


def judged(text: Column, forest: Forest) -> Column:
    """Array of (token, score) of the candidates of a text."""
    rows = F.transform(candidates(text), lambda c: F.struct(c["token"].alias("token"), features(c["token"], c["before"], c["after"]).alias("f")))
    return F.transform(rows, lambda r: F.struct(r["token"].alias("token"), forest(r["f"]).alias("score")))


def scan(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, finding, token_sha256, masked, n_chars, score, is_secret): one row for each candidate of each text."""
    forest = forest or Forest(labelled_findings(docs.sparkSession))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.posexplode(judged(F.col(text_col), forest)).alias("finding", "c"))
    token, score = F.col("c.token"), F.round("c.score", 6)
    return rows.select("doc_id", "finding", F.sha2(token, 256).alias("token_sha256"), F.concat(F.left(token, F.lit(4)), F.lit("...")).alias("masked"), F.length(token).alias("n_chars"), score.alias("score"), (score >= threshold).alias("is_secret"))


def redacted(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5, text_col: str = "text") -> DataFrame:
    """docs with every secret in the text column blanked out; all rows and columns stay."""
    forest = forest or Forest(labelled_findings(docs.sparkSession))
    secrets = F.filter(judged(F.col(text_col), forest), lambda c: F.round(c["score"], 6) >= threshold)
    clean = F.aggregate(secrets, F.col(text_col), lambda text, c: F.replace(text, c["token"], F.lit(BLANK)))
    return docs.withColumn(text_col, clean)
