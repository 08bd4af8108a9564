"""Secret scans: candidates by pattern, a random forest removes the false positives.

DataFrame functions and the JVM's forest learner only. Candidates are runs of 16 and more characters that
hold a digit, and whatever of six and more stands assigned to a name such as password, token or key. A run
without a digit that is assigned to no such name is no candidate: nothing tells it from a word.
Their features are length, character transitions and classes, dictionary coverage, path
and identifier shapes, and neighbouring words. The forest is trained from labelled findings and then
written out as expressions, so scanning is a single pass over the documents without a shuffle.

Labelled findings are a table (before, candidate, label). The corpus tables label none, so
``rule_findings`` makes a bounded set by rule: random material in the shapes of credentials, and
in the shapes that are usually mistaken for them. Pass another table to train on real findings.

Defined results: null and empty texts have no findings; rows repeated in the input are repeated in
the result; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from rpqframe.llm.common import fresh, pick
from rpqframe.llm.spans import matches

CANDIDATE = r"(?<![A-Za-z0-9_+/.-])(?=[A-Za-z_+/.-]*+[0-9])[A-Za-z0-9_+/.-]{16,}+={0,2}"
#: A name, what assigns, and the value.
NAMED = r"(?i)(?:passw(?:or)?d|passphrase|pwd|secret|token|credential|(?:api|access|private|auth)[_ -]?key)[\"'`]?\s{0,3}[:=]\s{0,3}[\"'`]?"
VALUE = r"[^\s\"'`<>,;(){}\[\]]{6,}"
WINDOW = 40

#: Dictionary of words that ordinary identifiers are made of.
DICTIONARY = (
    "account action address admin android apache application archive article assets backup branch build button cache center class client code com commit component config connection content "
    "control copy core count create data database date default delete demo design detail device dist doc document download draft dummy edit email error event example export file final folder form "
    "framework function group guide handler header history home html http image import index info input install item java json kernel label language layout library license link linux list local "
    "login main manager master media message meta method mode model module name network node number object office online option order org output package page part path phone photo placeholder plugin "
    "point policy post price product profile project public query read record release remote report request resource response result role root sample schema script search section select server "
    "service session setting shop site size source stable start state static status store string style support system table target task template test text theme time title token topic type update "
    "upload user util value version video view web widget window word write www year your"
).split()
NEAR_SECRET = r"(?i)(?:secret|token|passw(?:or)?d|pwd|api[_ -]?key|access[_ -]?key|private[_ -]?key|credential|bearer|authorization|auth)"
NEAR_HARMLESS = r"(?i)(?:commit|revision|checksum|sha-?1|sha-?256|md5|digest|hash|uuid|guid|integrity|etag|build|example|sample|version|isbn|doi|page|path|file)"
KNOWN_PREFIX = r"^(?:AKIA|ASIA|ghp_|gho_|github_pat_|sk-|sk_live_|xox[abp]-|glpat-|AIza|eyJ)"

FEATURES = ["length", "digits", "uppers", "switches", "variety", "hex_only", "dictionary", "path_parts", "near_secret", "near_harmless", "assigned", "uuid_shape", "known_prefix", "repeats", "date_shape"]


def features(cand: Column, before: Column) -> dict[str, Column]:
    n = F.length(cand).cast("double")
    count = lambda rx: F.regexp_count(cand, F.lit(rx)).cast("double")
    flag = lambda c: F.when(c, 1.0).otherwise(0.0)
    rest = F.regexp_replace(F.lower(cand), "(?:" + "|".join(sorted(DICTIONARY, key=lambda w: (-len(w), w))) + ")", "")
    return {
        "length": n,
        "digits": count("[0-9]") / n,
        "uppers": count("[A-Z]") / n,
        "switches": count("(?<=[0-9])[A-Za-z]|(?<=[A-Za-z])[0-9]|(?<=[a-z])[A-Z]") / n,
        "variety": F.size(F.array_distinct(F.split(cand, ""))).cast("double") / F.least(n, F.lit(64.0)),
        "hex_only": flag(cand.rlike("^[0-9a-f]+$")),
        "dictionary": (n - F.length(rest)) / n,
        "path_parts": count("[/.]"),
        "near_secret": flag(before.rlike(NEAR_SECRET)),
        "near_harmless": flag(before.rlike(NEAR_HARMLESS)),
        "assigned": flag(before.rlike("[=:]\\s*[\"'`]?$")),
        "uuid_shape": flag(cand.rlike("^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$")),
        "known_prefix": flag(cand.rlike(KNOWN_PREFIX)),
        "repeats": flag(cand.rlike("(.)\\1{4,}|01234|12345|abcde")),
        "date_shape": flag(cand.rlike("(?:19|20)\\d\\d[-/.][01]?\\d[-/.][0-3]?\\d")),
    }


#: Label, text before and candidate of each kind of finding; {h} hex digits, {H} upper case, {b} mixed base-64, {d} digits, {w} and {v} dictionary words.
KINDS = [
    (1, "token = \"", "{h40}"), (1, "secret: '", "{h32}"), (1, "api_key=", "{b40}"), (1, "password = \"", "{b20}"), (1, "access key ", "AKIA{H16}"), (1, "with ", "ghp_{b36}"),
    (1, "Authorization: Bearer ", "{b64}"), (1, "credential ", "sk-{b48}"), (1, "export TOKEN=", "{h64}"), (1, "key ", "AIza{b35}"), (1, "auth ", "eyJ{b60}"), (1, "private_key: ", "{b52}=="),
    (1, "password=", "{b10}"), (1, "pwd: ", "{b14}"), (1, "secret = '", "{h24}"), (0, "password: ", "{w}"), (0, "token = ", "{w}.{v}"), (0, "secret: ", "{w}_{v}"), (0, "password=", "{w}{v}"),
    (0, "commit ", "{h40}"), (0, "checksum: ", "{h32}"), (0, "sha256 = ", "{h64}"), (0, "id=", "{h8}-{h4}-{h4}-{h4}-{h12}"), (0, "see ", "/{w}/{v}/{w}{d2}/{v}.html"), (0, "file ", "{w}_{v}_{w}_{d4}"),
    (0, "on ", "{d4}-{d2}-{d2}T{d2}.{d2}.{d2}"), (0, "token = \"", "xxxxxxxxxxxxxxxx{d2}"), (0, "password: ", "example-{w}-{v}-{d2}"), (0, "call ", "{d20}"), (0, "call ", "{w}{v}{w}{v}{d2}"), (0, "version ", "{d1}.{d2}.{d4}-{w}.{v}"),
    (0, "the ", "www.{w}{v}{d2}.com/{w}"), (0, "mail ", "{w}.{v}.{d2}.{w}.com"), (0, "etag ", "{h32}"), (0, "page ", "{d16}"), (0, "secret of ", "{w}-{v}-{w}-{d2}"), (0, "token type ", "{w}/{v}/{w}/{d2}.{v}"),
]


def rule_findings(spark: SparkSession, per_kind: int = 60) -> DataFrame:
    """A bounded set of labelled findings made by rule from digests of row numbers."""
    i = F.col("i")
    salt = lambda k, s: F.concat_ws(":", i.cast("string"), F.lit(str(k)), F.lit(s))
    stream = lambda k, s: F.concat(F.sha2(salt(k, s + "a"), 256), F.sha2(salt(k, s + "b"), 256))
    coded = lambda k, s: F.regexp_replace(F.base64(F.unhex(stream(k, s))), "[+/=]", "x")
    words = F.array(*[F.lit(w) for w in DICTIONARY])
    parts = []
    for k, (label, before, shape) in enumerate(KINDS):
        bits = []
        for j, (lit, kind, size) in enumerate(re.findall(r"([^{]+)|\{([hHbdwv])(\d*)\}", shape)):
            if lit:
                bits.append(F.lit(lit))
                continue
            n = int(size or 0)
            made = {
                "h": lambda: F.left(stream(k, f"{j}"), F.lit(n)), "H": lambda: F.upper(F.left(coded(k, f"{j}"), F.lit(n))), "b": lambda: F.left(coded(k, f"{j}"), F.lit(n)),
                "d": lambda: F.left(F.regexp_replace(stream(k, f"{j}"), "[a-f]", ""), F.lit(n)),
                "w": lambda: words[F.pmod(F.hash(salt(k, f"{j}")), len(DICTIONARY))], "v": lambda: words[F.pmod(F.hash(salt(k, f"{j}v")), len(DICTIONARY))],
            }[kind]()
            bits.append(made)
        parts.append(F.struct(F.lit(before).alias("before"), F.concat(*bits).alias("candidate"), F.lit(float(label)).alias("label")))
    rows = spark.range(per_kind).withColumnRenamed("id", "i").select(F.explode(F.array(*parts)).alias("x"))
    return rows.select("x.*")


def feature_rows(findings: DataFrame) -> DataFrame:
    """features (a vector) and label of each finding."""
    from pyspark.ml.feature import VectorAssembler

    rows = findings.select("label", *[c.alias(k) for k, c in features(F.col("candidate"), F.col("before")).items()])
    return VectorAssembler(inputCols=FEATURES, outputCol="features").transform(rows)


def fit_forest(findings: DataFrame, trees: int = 24, depth: int = 6, seed: int = 11, max_findings: int = 200_000):
    """The learner's model of at most ``max_findings`` findings, those of least hash; in one partition, so that the draws do not depend on the cluster."""
    from pyspark.ml.classification import RandomForestClassifier

    some = findings.orderBy(F.xxhash64("before", "candidate"), "before", "candidate", "label").limit(max_findings).coalesce(1)
    return RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="onethird").fit(feature_rows(some).select("features", "label"))


def train_forest(findings: DataFrame, trees: int = 24, depth: int = 6, seed: int = 11, max_findings: int = 200_000) -> list[str]:
    """One SQL expression over the feature names for each tree; its value is the tree's vote (0 or 1)."""
    return [tree_sql(t.toDebugString) for t in fit_forest(findings, trees, depth, seed, max_findings).trees]


def tree_sql(text: str) -> str:
    """The printed tree as nested CASE expressions."""
    lines = [x.strip() for x in text.splitlines()[1:] if x.strip()]

    def build(at: int) -> tuple[str, int]:
        if m := re.match(r"Predict: (\S+)", lines[at]):
            return m[1] + "D", at + 1
        k, op, v = re.match(r"If \(feature (\d+) (<=|<) (\S+)\)", lines[at]).groups()
        yes, at = build(at + 1)
        no, at = build(at + 1)  # the line between is the Else
        return f"(CASE WHEN f.{FEATURES[int(k)]} {op} {float(v)!r}D THEN {yes} ELSE {no} END)", at

    return build(0)[0]


def scan(docs: DataFrame, forest: list[str], id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.5) -> DataFrame:
    """id_col, findings: array<struct<s,e,m,p>> of all candidates with place, text and share of votes; secrets: those kept."""
    src = pick(docs, id_col, text_col).toDF("id", "text").withColumn("text", F.coalesce(F.col("text").cast("string"), F.lit("")))
    none = F.array().cast("array<struct<s:int,e:int,m:string>>")
    runs = F.when(F.col("text").rlike(CANDIDATE), matches(F.col("text"), F.lit(CANDIDATE))).otherwise(none)
    own = lambda c: F.regexp_replace(c["m"], "^" + NAMED, "")
    named = F.transform(matches(F.col("text"), F.lit(NAMED + VALUE)), lambda c: F.struct((c["e"] - F.length(own(c))).alias("s"), c["e"].alias("e"), own(c).alias("m")))
    named = F.when(F.col("text").rlike(NAMED + VALUE), named).otherwise(none)
    cands = F.when(F.size(named) > 0, F.sort_array(F.array_union(named, runs))).otherwise(runs)
    before = lambda c: F.substring(F.col("text"), F.greatest(F.lit(1), c["s"] + 1 - WINDOW), F.least(F.lit(WINDOW), c["s"]))
    feats = F.transform("cands", lambda c: F.struct(c["s"].alias("s"), c["e"].alias("e"), c["m"].alias("m"), F.struct(*[v.alias(k) for k, v in features(c["m"], before(c)).items()]).alias("f")))
    votes = " + ".join(t.replace("f.", "x.f.") for t in forest)
    found = F.expr(f"transform(feats, x -> named_struct('s', x.s, 'e', x.e, 'm', x.m, 'p', round(({votes}) / {float(len(forest))}D, 6)))")
    out = src.withColumn("cands", cands).withColumn("feats", feats).withColumn("findings", found)
    return out.select(F.col("id").alias(id_col), "findings", F.filter("findings", lambda f: f["p"] >= threshold).alias("secrets"))


def merged(spans: Column) -> Column:
    """Sorted places without those that start within an earlier one; the earlier one takes in what sticks out."""
    first = F.array(F.struct(F.lit(0).alias("s"), F.lit(0).alias("e")))
    last = lambda acc: F.element_at(acc, -1)
    both = lambda acc, x: F.concat(F.slice(acc, F.lit(1), F.size(acc) - 1), F.array(F.struct(last(acc)["s"].alias("s"), F.greatest(last(acc)["e"], x["e"]).alias("e"))))
    return F.aggregate(spans, first, lambda acc, x: F.when(x["s"] < last(acc)["e"], both(acc, x)).otherwise(F.concat(acc, F.array(F.struct(x["s"].alias("s"), x["e"].alias("e"))))))


def redact(docs: DataFrame, forest: list[str], text_col: str = "text", threshold: float = 0.5, mark: str = "[secret]") -> DataFrame:
    """The documents with a mark in the place of every kept secret; the same characters elsewhere stay, and so do texts without one."""
    row, spans = fresh("row", docs), fresh("spans", docs)
    keys = docs.withColumn(row, F.struct(*[F.col(f"`{c}`") for c in docs.columns]))
    found = scan(keys, forest, row, text_col, threshold).withColumn(spans, merged("secrets"))
    text, at = F.col(f"{row}.`{text_col}`"), F.col(spans)
    gap = lambda x, i: F.substring(text, x["e"] + 1, F.coalesce(F.get(at, i + 1)["s"], F.length(text)) - x["e"])
    masked = F.when(F.size("secrets") == 0, text).otherwise(F.array_join(F.transform(at, gap), mark))
    return found.select(*[(masked if c == text_col else F.col(f"{row}.`{c}`")).alias(c) for c in docs.columns])
