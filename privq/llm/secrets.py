"""Secret scan: a random forest removes false positives among candidate strings. DataFrame functions only.

A candidate is a run of at least 12 characters of ``A-Za-z0-9+/_-`` (with up to two closing ``=``) that has a digit,
16 capitals, or capitals after small letters. One regular expression marks all candidates of a text; the marked text is
split, and features are computed in the row by higher-order functions: length, shares and transitions of character
classes, dictionary coverage, shape, path, and neighbouring words. The forest is trained on labelled findings and
compiled to CASE expressions, so scoring and redaction are one narrow pass without a shuffle. Only character offsets
(``scan``) need the rows of a document together, and these hold no text.

``labelled_findings`` builds the default training set: keyed hashes fill known forms of secrets and of things that look
like them. Any frame with the columns value, before, after, path, label can take its place.

Null and empty texts have no findings. Repeated rows give repeated findings. A text that holds U+FDD0 or U+FDD1 (never
characters of text) has them read as U+FFFD, and keeps them unless something in it is redacted. Secrets themselves are
never returned, only their digests.
"""

from __future__ import annotations

import re

from pyspark.ml.classification import RandomForestClassificationModel, RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from privq.llm.common import table, text_or_empty

CANDIDATE = r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*[0-9]|[A-Z]{16}|[a-z+/_-]*[A-Z]+[a-z]+[A-Z])[A-Za-z0-9+/_-]{12,}={0,2}"
OPEN, CLOSE = "\ufdd0", "\ufdd1"
REDACTED = "[SECRET]"
NEAR = 40
TREES, DEPTH = 15, 6
FINDINGS_PER_FORM = 250
#: Words that cover identifiers and placeholders, and words that stand near secrets or near other codes.
WORDS = "account action address admin after api app array base build button cache call change check class client code column common config content context count create current data date default delete description dist document edit element email end error event example fake field file filter first folder form format from function get group handler header here home id image index info input insert integer internal international item key language last left lib license line link list load local main manager map message method model module name new node note null number object open option order package page parent password path place point post print process product project property public query read record release replace request response result return right root row sample save score search secret section select send server service session set size sort source start state status store string style sub system table tag target temp test text the time title token tool tree type update upload url user value version view web window word your".split()
SECRET_WORDS = "access_key api_key apikey auth authorization bearer credential credentials passphrase passwd password private_key pwd secret secret_key token".split()
BENIGN_WORDS = "account build call card checksum commit digest dummy etag example fake fax hash id isbn md5 number order phone placeholder ref rev revision sample sha sha1 sha256 test trace uuid version".split()

#: Each feature of a candidate ``x`` (value, before, after, path) as SQL.
FEATURES = {
    "length": "length(x.value)",
    "digits": "regexp_count(x.value, '[0-9]') / length(x.value)",
    "capitals": "regexp_count(x.value, '[A-Z]') / length(x.value)",
    "smalls": "regexp_count(x.value, '[a-z]') / length(x.value)",
    "marks": "regexp_count(x.value, '[^A-Za-z0-9]') / length(x.value)",
    "turns": "regexp_count(x.value, '(?<=[a-z])(?=[^a-z])|(?<=[A-Z])(?=[^A-Z])|(?<=[0-9])(?=[^0-9])') / length(x.value)",
    "distinct_chars": "size(array_distinct(split(x.value, ''))) / length(x.value)",
    "hexadecimal": "IF(x.value rlike '^([0-9a-f]+|[0-9A-F]+)$', 1, 0)",
    "number": "IF(x.value rlike '^[0-9+/_-]+$', 1, 0)",
    "longest_number": "array_max(transform(split(x.value, '[^0-9]+'), s -> length(s)))",
    "longest_letters": "array_max(transform(split(x.value, '[^A-Za-z]+'), s -> length(s)))",
    "covered": f"1 - length(regexp_replace(lower(x.value), '{'|'.join(sorted(WORDS, key=lambda w: (-len(w), w)))}', '')) / length(x.value)",
    "uuid": "IF(x.value rlike '^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$', 1, 0)",
    "slashes": "regexp_count(x.value, '/')",
    "in_path": "IF(x.before rlike '(://[^ ]*|[/.@])$', 1, 0)",
    "file_path": "IF(lower(coalesce(x.path, '')) rlike '(^|[/_.-])(tests?|examples?|fixtures?|docs?|samples?|mocks?)([/_.-]|$)', 1, 0)",
    "secret_words": f"regexp_count(lower(x.before), '(?<![a-z])({'|'.join(SECRET_WORDS)})(?![a-z])')",
    "benign_words": f"regexp_count(lower(x.before), '(?<![a-z])({'|'.join(BENIGN_WORDS)})(?![a-z])')",
    "benign_after": f"regexp_count(lower(x.after), '(?<![a-z])({'|'.join(BENIGN_WORDS)})(?![a-z])')",
    "assigned": "IF(x.before rlike '[=:] ?[\"`]?$', 1, 0)",
    "quoted": "IF(x.after rlike '^[\"`]', 1, 0)",
    "issuer": "IF(x.value rlike '^(AKIA|ASIA|gh[opsu]_|glpat-|sk-|xox[abp]-|AIza|eyJ)', 1, 0)",
}


def _pick(salt: int, *options: str) -> str:
    """SQL: one of some strings by a hash of the row."""
    return f"element_at(array({', '.join(options)}), 1 + CAST(pmod(xxhash64(id, {salt}), {len(options)}) AS INT))"


def labelled_findings(spark: SparkSession, per_form: int = FINDINGS_PER_FORM) -> DataFrame:
    """value, before, after, path, label: forms of secrets (1) and of look-alikes (0), filled by hashes of row ids."""
    hexa = "concat(sha2(concat(id, '-a'), 256), sha2(concat(id, '-b'), 256))"
    plain = f"translate(base64(unhex({hexa})), '+/=\\r\\n', 'Xq')"
    capital = f"translate(upper({plain}), '0189', 'GHJK')"
    digit = f"translate({hexa}, 'abcdef', '314159')"
    size = lambda lo, hi: f"{lo} + CAST(pmod(xxhash64(id, 77), {hi - lo + 1}) AS INT)"
    syllable = lambda salt: _pick(salt, *[f"'{s}'" for s in "the er ti on wh and ing re st ou ly en ach ver ung que eau ci la os".split()])
    prose = f"concat({syllable(1)}, {syllable(2)}, ' ', {syllable(3)}, {syllable(4)}, {syllable(5)}, ' ', {syllable(6)}, ' ')"
    word = lambda salt: _pick(salt, *[f"'{w}'" for w in WORDS if len(w) > 3][:100])
    assign = lambda salt, *names: f"concat({prose}, {_pick(salt, *[f"'{n}'" for n in names])}, {_pick(salt + 1, "'='", "' = '", "': '", "'=\"'", "' = \"'")})"
    keyed = ("api_key", "API_KEY", "secret", "token", "auth_token", "client_secret", "password", "access_key")
    forms = [
        (1, f"concat('AKIA', substr({capital}, 1, 16))", _pick(5, prose, prose, assign(6, "aws_access_key_id", "key"))),
        (1, f"substr({hexa}, 1, {size(14, 40)})", assign(7, "password", "passwd", "pwd", "db_password")),
        (1, f"substr({hexa}, 1, 40)", assign(8, "token", "auth_token", "secret", "api_key")),
        (1, f"substr({plain}, 1, {size(20, 64)})", assign(9, *keyed)),
        (1, f"concat({_pick(10, "'ghp_'", "'sk-'", "'glpat-'", "'xoxb-'", "'AIza'")}, substr({plain}, 1, {size(24, 40)}))", _pick(11, prose, assign(12, *keyed))),
        (1, f"substr({plain}, 1, {size(16, 48)})", f"concat({prose}, {_pick(13, "'Authorization: Bearer '", "'credential '", "'secret is '", "'password '")})"),
        (0, f"substr({digit}, 1, {size(12, 20)})", _pick(14, prose, prose, f"concat({prose}, 'card ')", f"concat({prose}, 'phone ')", assign(15, "id", "number"))),
        (0, f"substr({hexa}, 1, 40)", f"concat({prose}, {_pick(16, "'commit '", "'rev '", "'sha1 '", "'sha: '", "'commit/'")})"),
        (0, f"substr({hexa}, 1, {_pick(17, '32', '64')})", f"concat({prose}, {_pick(18, "'md5 '", "'checksum: '", "'sha256:'", "'digest='", "'etag: '", "'hash '")})"),
        (0, f"concat(substr({hexa}, 1, 8), '-', substr({hexa}, 9, 4), '-', substr({hexa}, 13, 4), '-', substr({hexa}, 17, 4), '-', substr({hexa}, 21, 12))", _pick(19, prose, assign(20, "id", "uuid", "trace", "request"))),
        (0, _pick(21, "'YOUR_API_KEY_HERE'", "'example_token_1234'", "'your-secret-key-1'", "'changeme12345'", "'xxxxxxxxxxxx0000'", "'REPLACE_WITH_TOKEN1'", "'test_password_123'", "'000000000000000000'"), assign(22, *keyed)),
        (0, f"concat({word(23)}, initcap({word(24)}), initcap({word(25)}), {_pick(26, "'2'", "''", "'V3'", "'Id'")})", _pick(27, prose, f"concat({prose}, 'self.')", assign(28, "name", "call"))),
        (0, f"upper(concat({syllable(31)}, {syllable(32)}, {syllable(33)}, {syllable(34)}, {syllable(35)}, {syllable(36)}, {syllable(37)}, {syllable(38)}))", f"upper({prose})"),
        (0, f"concat({word(41)}, '/', {word(42)}, '/', {word(43)}, {_pick(44, "'3'", "'2'", "'64'")}, '/', {word(45)})", f"concat({prose}, {_pick(46, "'/'", "'https://host.org/'", "'../'", "''")})"),
        (0, f"concat({_pick(47, "'2024-01-15T'", "'release-2023-'", "'v1-20240311-'", "'20231105T'")}, substr({digit}, 1, 6))", prose),
        (0, f"concat(initcap({syllable(51)}), {syllable(52)}, initcap({syllable(53)}), {syllable(54)}, initcap({syllable(55)}), {syllable(56)}, {syllable(57)})", prose),
        (0, f"substr({plain}, 1, {size(16, 44)})", f"concat({prose}, {_pick(58, "'dummy '", "'example: '", "'sample='", "'placeholder '")})"),
    ]
    made = None
    for k, (label, value, before) in enumerate(forms):
        path = _pick(61, "NULL", "'src/app/main.py'", "'deploy/config.yml'") if label else _pick(62, "NULL", "'tests/fixtures/data.json'", "'src/app/main.py'", "'docs/guide.md'")
        rows = spark.range(k * per_form, (k + 1) * per_form).selectExpr(f"{value} AS value", f"{before} AS before", f"concat({_pick(63, "'\"'", "' '", "'.'")}, ' ', {prose}) AS after", f"CAST({path} AS STRING) AS path", f"{label} AS label")
        made = rows if made is None else made.union(rows)
    return made


def compile_forest(debug: str, names: list[str]) -> list[str]:
    """Trees of a fitted forest, from its printed form, as SQL CASE expressions over ``x``."""
    lines = [(len(s) - len(s.lstrip()), s.strip()) for s in debug.splitlines()]
    at = 0

    def node(depth: int) -> str:
        nonlocal at
        _, line = lines[at]
        at += 1
        if m := re.match(r"Predict: ([\d.]+)", line):
            return f"{int(float(m[1]))}"
        m = re.match(r"If \(feature (\d+) <= ([-\d.eE]+)\)", line)
        yes = node(depth + 1)
        at += 1  # the matching Else
        no = node(depth + 1)
        return f"IF(x.{names[int(m[1])]} <= {float(m[2])!r}D, {yes}, {no})"

    trees = []
    while at < len(lines):
        if lines[at][1].startswith("Tree "):
            at += 1
            trees.append(node(0))
        else:
            at += 1
    return trees


def measured(findings: DataFrame) -> DataFrame:
    """``x`` (all features), features as a vector, and label of labelled findings."""
    x = findings.select(F.struct("value", "before", "after", "path").alias("x"), "label")
    rows = x.select(*[F.expr(f"CAST({sql} AS DOUBLE)").alias(n) for n, sql in FEATURES.items()], F.col("label").cast("double").alias("label"))
    ready = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(rows)
    return ready.select(F.struct(*FEATURES).alias("x"), "features", "label")


def fit_forest(findings: DataFrame, seed: int = 7) -> RandomForestClassificationModel:
    forest = RandomForestClassifier(numTrees=TREES, maxDepth=DEPTH, featureSubsetStrategy="sqrt", seed=seed)
    return forest.fit(measured(findings).select("features", "label"))


def train(findings: DataFrame, seed: int = 7) -> list[str]:
    """Compiled trees; ``findings`` is a bounded set of labelled rows."""
    return compile_forest(fit_forest(findings, seed).toDebugString, list(FEATURES))


_default_trees: dict[tuple[int, str | None, int], list[str]] = {}


def default_trees(spark: SparkSession, seed: int = 7) -> list[str]:
    """Compiled trees of the default findings, trained once a process: they depend on no table, only on the seed and on
    the parts that a session makes of them, and each training leaves generated classes in the driver."""
    made = (spark.sparkContext.defaultParallelism, spark.conf.get("spark.sql.leafNodeDefaultParallelism", None), seed)
    if made not in _default_trees:
        _default_trees[made] = train(labelled_findings(spark), seed)
    return _default_trees[made]


def _scored(df: DataFrame, trees: list[str], text: str, path: str | None) -> DataFrame:
    """``df`` with __pieces (text between candidates) and __found (value, rest, score), candidate by candidate."""
    kept = F.translate(text_or_empty(text), OPEN + CLOSE, "\ufffd\ufffd")
    marked = df.withColumn("__pieces", F.split(F.regexp_replace(kept, CANDIDATE, OPEN + "$0" + CLOSE), OPEN))
    where = "CAST(NULL AS STRING)" if path is None else f"CAST(`{path}` AS STRING)"
    n = "size(__pieces) - 1"
    near = f"struct(substring_index(p, '{CLOSE}', 1) AS value, right(replace(b, '{CLOSE}', ''), {NEAR}) AS before, left(substring_index(p, '{CLOSE}', -1), {NEAR}) AS after, {where} AS path, substring_index(p, '{CLOSE}', -1) AS rest)"
    cut = marked.withColumn("__found", F.expr(f"zip_with(slice(__pieces, 1, {n}), slice(__pieces, 2, {n}), (b, p) -> {near})"))
    measured = ", ".join(f"CAST({sql} AS DOUBLE) AS {name}" for name, sql in FEATURES.items())
    cut = cut.withColumn("__found", F.expr(f"transform(__found, x -> struct(x.value AS value, x.rest AS rest, {measured}))"))
    votes = " + ".join(trees)
    return cut.withColumn("__found", F.expr(f"transform(__found, x -> struct(x.value AS value, x.rest AS rest, ({votes}) / {len(trees)}D AS score))"))


def scan(df: DataFrame, trees: list[str], text: str = "text", carry: tuple[str, ...] = ("doc_id",), path: str | None = None) -> DataFrame:
    """One row per candidate: ``carry``, offsets in characters (end exclusive), digest, score, is_secret."""
    inner = [*dict.fromkeys([*carry, text, *([path] if path else [])])]
    scored = _scored(df.select(*inner), trees, text, path).where("size(__found) > 0").withColumn("__row", F.monotonically_increasing_id())
    rows = scored.select(*carry, "__row", F.length(F.element_at("__pieces", 1)).alias("__lead"), F.posexplode(F.expr("transform(__found, x -> struct(x.value AS value, length(x.value) + length(x.rest) AS width, x.score AS score))")).alias("__k", "x"))
    slim = rows.select(*carry, "__row", "__lead", "__k", F.length("x.value").alias("__n"), F.sha2("x.value", 256).alias("value_sha256"), "x.width", "x.score")
    before = Window.partitionBy("__row").orderBy("__k").rowsBetween(Window.unboundedPreceding, -1)
    start = (F.col("__lead") + F.coalesce(F.sum("width").over(before), F.lit(0))).cast("long")
    placed = slim.withColumn("start", start)
    return placed.select(*carry, "start", (F.col("start") + F.col("__n")).alias("end"), "value_sha256", "score", (F.col("score") >= 0.5).alias("is_secret"))


def redact(df: DataFrame, trees: list[str], text: str = "text", path: str | None = None) -> DataFrame:
    """``df`` with secrets in ``text`` replaced; texts without a secret stay as they are."""
    scored = _scored(df, trees, text, path)
    rebuilt = F.expr(f"concat(__pieces[0], array_join(transform(__found, x -> concat(IF(x.score >= 0.5, '{REDACTED}', x.value), x.rest)), ''))")
    changed = F.when(F.expr("exists(__found, x -> x.score >= 0.5)"), rebuilt).otherwise(F.col(text))
    return scored.withColumn(text, changed).select(*df.columns)


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All candidates of whole ``documents`` with the forest's verdict."""
    return scan(table(spark, sf_dir, "documents").select("doc_id", "text"), train(labelled_findings(spark)))
