"""Secret scan: pattern candidates, then a random forest that removes false positives.

Candidates, their places and their surroundings come from regular expressions
on the JVM. They are wide: private keys, values assigned to a name that means a
secret, long strings with digits (so also numbers, addresses, versions and
digests), and very long words; what of them is a secret, the forest says. It
looks at a candidate's length, how likely its character transitions are in
secrets and in other findings, how much of it dictionary words cover, the path
it stands in and the words beside it. Transitions are counted on one half of
the labelled findings, the forest is fitted on the other, on the driver (a
bounded table), and both become SQL expressions, so scoring needs neither
Python nor a shuffle of texts.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_NAMES = r"(?:pass(?:word|wd|phrase)?|pwd|secret|token|api[_-]?key|access[_-]?key|private[_-]?key|auth|bearer|credentials?)"
_ASSIGNED = r"(?<=[=:\"'] {0,2})(?<=(?i:" + _NAMES + r")[A-Za-z0-9_-]{0,12}[\"']? {0,2}[=:]{1,2} {0,2}[\"']?)(?!(?i:bearer|basic) )[A-Za-z0-9@!^~+/_.$%&*#?-]{5,}[A-Za-z0-9@!^~+/_$%&*#?-]={0,2}"
_TOKEN = r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_.@-]*+[0-9])(?=[A-Za-z0-9+/_.@-]{12})[A-Za-z0-9+/_-]++(?:[.@][A-Za-z0-9+/_-]++)*+={0,2}"
_LONG = r"(?<![A-Za-z0-9+/_-])[A-Za-z+/_-]{24,}+"
_PEM = r"-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----"
CANDIDATE = f"(?:{_PEM}|{_ASSIGNED}|{_TOKEN}|{_LONG})"
CONTEXT_CHARS = 48

#: Fixed word lists of the features.
SECRET_WORDS = "password passwd passphrase pwd secret token apikey api_key api-key access_key access-key auth bearer credential private key".split()
BENIGN_WORDS = "sha sha1 sha256 md5 checksum hash commit revision digest integrity etag version release uuid guid example sample dummy placeholder test fixture build id isbn".split()
TEST_PATHS = "test tests example examples sample fixture fixtures doc docs mock lock sum changelog vendor".split()
DICTIONARY = "access account admin alpha backup base beta block build byte cache change check class client cloud code config connect content context control count create data date default delete demo deploy description dev document edit email entry error event example export feature field file final find first folder format frame function group header home host image import index info input issue item java json key label language last layout level library line link list local log main master message meta method model module month name network node note number object order output package page param part password path pattern phase place plan port post prefix private process product production profile project property public query read record release remote report request reset resource response result role root route rule sample schema script search secret section select server service session setting size source stage start state status step string style system table target task temp template test text theme thread time title token type unicode unit update upload user util value vector version video view web week window word work year your".split()
MOCK_WORDS = "example sample dummy placeholder changeme change-me your xxxx test mock fake redacted todo 12345678 none null required undefined string".split()
SYMBOLS = "abcdefghijklmnopqrstuvwxyz0."  # a digit is 0, any other character a dot


@dataclass(frozen=True)
class ForestParams:
    """``findings`` bounds the labelled rows that training collects."""

    trees: int = 21
    depth: int = 7
    findings: int = 4_000
    seed: int = 3


FEATURES = ["length", "distinct", "changes", "digits", "capitals", "marks", "dots", "hexadecimal", "transitions", "dictionary", "runs", "mock", "prefixed", "secret_word", "benign_word", "test_path", "assigned"]


def _symbols(candidate: Column) -> Column:
    return F.regexp_replace(F.translate(F.lower(candidate), "123456789", "000000000"), "[^a-z0]", ".")


def transition_odds(findings: DataFrame, most: int = 2_000) -> list[float]:
    """Log odds of each pair of symbols in secrets against other findings, from at most ``most`` of them."""
    rows = findings.orderBy(F.xxhash64("candidate", "before"), "candidate").limit(most).select(_symbols(F.col("candidate")).alias("s"), "label").collect()
    seen = np.ones((2, len(SYMBOLS), len(SYMBOLS)))
    place = {c: i for i, c in enumerate(SYMBOLS)}
    for r in rows:
        for x, y in zip(r["s"], r["s"][1:], strict=False):
            seen[int(r["label"]), place[x], place[y]] += 1
    chance = seen / seen.sum(axis=2, keepdims=True)
    return [round(float(v), 6) for v in (np.log(chance[1]) - np.log(chance[0])).ravel()]


def _mean_odds(candidate: Column, odds: list[float]) -> Column:
    """The mean log odds of a candidate's transitions, in one pass over its pairs."""
    code = lambda c: F.when(c == "0", 27).when(c == ".", 28).otherwise(F.ascii(c) - 96)
    pairs = F.regexp_extract_all(_symbols(candidate), F.lit("(?s)(?=(..))"), F.lit(1))
    table = F.lit(odds)
    total = F.aggregate(pairs, F.lit(0.0), lambda acc, p: acc + F.element_at(table, ((code(F.left(p, F.lit(1))) - 1) * 28 + code(F.right(p, F.lit(1)))).cast("int")))
    return total / F.greatest(F.size(pairs), F.lit(1))


def features(found: DataFrame, odds: list[float]) -> DataFrame:
    """Add a column for each of FEATURES to rows with candidate, before, after, path."""
    c, low = F.col("candidate"), F.lower("candidate")
    n = F.greatest(F.length(c), F.lit(1)).cast("double")
    before = F.lower(F.coalesce("before", F.lit("")))
    beside = F.lower(F.concat_ws(" ", F.col("before"), F.col("after")))
    without = lambda text, pattern: F.length(F.regexp_replace(text, pattern, "")).cast("double")
    words = "|".join(sorted(DICTIONARY, key=len, reverse=True))
    whole = lambda names: r"(?<![a-z0-9])(?:" + "|".join(names) + r")(?![a-z0-9])"
    return found.withColumns({
        "length": n,
        "distinct": F.size(F.array_distinct(F.split(c, ""))).cast("double") / n,
        "changes": F.length(F.regexp_replace(c, "[a-z]+|[A-Z]+|[0-9]+|[^A-Za-z0-9]+", "#")).cast("double") / n,
        "digits": 1 - without(c, "[0-9]") / n,
        "capitals": 1 - without(c, "[A-Z]") / n,
        "marks": 1 - without(c, "[^A-Za-z0-9]") / n,
        "dots": n - without(c, "[.@]"),
        "hexadecimal": c.rlike("^(?:[0-9a-f]+|[0-9A-F]+)$").cast("double"),
        "transitions": _mean_odds(c, odds),
        "dictionary": 1 - without(low, words) / n,
        "runs": 1 - without(low, r"(.)\1{2,}|0123|1234|2345|3456|4567|5678|6789|abcd|bcde|cdef|qwer|asdf") / n,
        "mock": low.rlike("(?:" + "|".join(MOCK_WORDS) + ")").cast("double"),
        "prefixed": c.rlike("^(?:-----BEGIN |(?:AKIA|ASIA|AGPA)[A-Z0-9]{12}|gh[pousr]_|glpat-|xox[abp]-|sk_live_|eyJ)").cast("double"),
        "secret_word": before.rlike("(?:" + "|".join(SECRET_WORDS) + ")").cast("double"),
        "benign_word": beside.rlike(whole(BENIGN_WORDS)).cast("double"),
        "test_path": F.lower(F.coalesce("path", F.lit(""))).rlike(whole(TEST_PATHS)).cast("double"),
        "assigned": before.rlike(_NAMES + r"[a-z0-9_-]{0,12}[\"']? {0,2}[=:]{1,2} {0,2}[\"']?$").cast("double"),
    })


def labelled_findings(spark: SparkSession, rows: int = 4_000) -> DataFrame:
    """Labelled findings by rule: candidate, before, after, path, label.

    One in two is a key as services issue them (hexadecimal, base 64, prefixed
    capitals, private keys) or a password, bare or assigned. The others are
    what scanners raise in error: digests and commit ids named as such, card
    and telephone numbers, network and mail addresses, versions, identifiers,
    paths, dates, long words, documentation keys, placeholders and keyboard
    runs.
    """
    i, kind = F.col("id"), F.pmod(F.shiftright("id", 1), F.lit(16))
    h = F.sha2(F.concat(F.lit("finding:"), i.cast("string")), 256)
    number = lambda salt, n: F.pmod(F.xxhash64("id", F.lit(salt)), F.lit(n))
    pick = lambda names, salt: F.element_at(F.array(*[F.lit(x) for x in names]), (number(salt, len(names)) + 1).cast("int"))
    w = lambda salt: pick(DICTIONARY, salt)
    digits = number(90, 10_000).cast("string")
    base64 = F.regexp_replace(F.base64(F.unhex(F.substring(h, 1, 48))), "=", "")
    capitals = F.translate(F.upper(F.substring(F.base64(F.unhex(h)), 1, 16)), "+/", "XQ")
    prefix = pick(["AKIA", "ASIA", "AGPA"], 1)
    octet = lambda salt: number(salt, 256).cast("string")
    chosen = lambda options: F.coalesce(*[F.when(kind == k, v) for k, v in enumerate(options)])
    letters = F.translate(F.substring(h, 1, 40), "0123456789", "ghijklmnop")
    true = chosen([
        F.substring(h, 1, 40), F.upper(F.substring(h, 1, 40)), F.substring(h, 1, 32), F.substring(h, 1, 18), base64, F.concat(prefix, capitals),
        F.concat(pick(["ghp_", "sk_live_", "xoxb-", "glpat-"], 2), F.substring(base64, 1, 30)), F.concat(F.substring(h, 1, 6), F.upper(F.substring(h, 7, 6)), F.substring(base64, 1, 8)),
        F.concat(F.initcap(w(40)), F.lit("20"), F.lpad(number(41, 100).cast("string"), 2, "0"), pick(["!", "#", "$", "?"], 42)), F.concat(w(43), w(44), w(45)), F.concat(w(46), digits, pick(["!", "*", "_", "@"], 47)), F.substring(letters, 1, 16),
        F.substring(letters, 1, 32), F.lit("-----BEGIN RSA PRIVATE KEY-----"), F.concat(F.lit("eyJ"), F.substring(base64, 1, 20), F.lit(".eyJ"), F.substring(base64, 5, 20), F.lit("."), F.substring(h, 1, 20)), F.concat(F.substring(base64, 1, 10), pick(["!", "$", "%", "^"], 48), F.substring(base64, 11, 6)),
    ])
    false = chosen([
        F.substring(h, 1, 40), F.concat_ws("-", w(3), w(4), digits), F.concat_ws("_", w(5), w(6), F.concat(w(7), digits)), F.concat_ws("/", w(8), w(9), F.concat(w(10), digits)),
        F.concat(pick(["your", "my", "change", "example", "dummy"], 11), F.lit("-"), w(12), F.lit("-0000"), digits), pick(["xxxxxxxxxxxx1234", "1234567890abcdef", "abcdef123456789", "aaaaaaaaaaaa0000", "qwertyuiop1234", "password123456", "changeme", "placeholder", "required", "undefined", "string", "********"], 13),
        F.concat(F.lit("2023-0"), F.substring(digits, 1, 1), F.lit("-1"), F.substring(digits, 2, 1), F.lit("T10-20-3"), F.substring(digits, 1, 1)), F.concat(F.initcap(w(14)), F.initcap(w(15)), F.initcap(w(16)), digits),
        F.substring(F.translate(h, "abcdef", "123456"), 1, 16), F.concat_ws(".", octet(50), octet(51), octet(52), octet(53)), F.concat(w(54), F.lit("."), digits, F.lit("@"), w(55), F.lit(".example.com")), F.concat(w(56), w(57), w(58), w(59), w(60)),
        F.concat(prefix, F.substring(capitals, 1, 9), F.lit("EXAMPLE")), F.concat_ws("-", F.substring(h, 1, 8), F.substring(h, 9, 4), F.substring(h, 13, 4), F.substring(h, 17, 4), F.substring(h, 21, 12)), F.concat(w(61), F.lit("-v"), number(62, 20).cast("string"), F.lit("."), number(63, 30).cast("string"), F.lit("."), digits), F.concat_ws("-", F.lit("+49"), F.substring(F.translate(h, "abcdef", "123456"), 1, 4), F.substring(F.translate(h, "abcdef", "123456"), 5, 8)),
    ])
    name = pick(["token", "password", "secret", "api_key", "auth_token", "access_key", "client_secret", "DB_PASSWORD", "passwd", "pwd", "Token", "API-KEY"], 20)
    cue = F.concat(name, pick(["=", " = ", ": ", '="', ' = "', ": '", '": "'], 21))
    prose = F.concat(w(22), F.lit(" "), w(23), pick([" ", ", ", ".\n", " | "], 24))
    digest = F.concat(pick(["commit ", "sha256: ", "checksum ", "sha1 ", "md5 ", "revision ", "integrity ", "digest = ", "etag: "], 25))
    is_true = F.pmod(i, F.lit(2)) == 0
    known = kind.isin(5, 6, 13, 14)  # known by their form, so often bare
    before_true = F.when(known & (number(30, 3) > 0), prose).otherwise(F.concat(prose, cue))
    before_false = F.when(kind.isin(0, 13), F.concat(prose, digest)).when(kind.isin(4, 5, 12) & (number(31, 2) == 0), F.concat(prose, cue)).otherwise(prose)
    return spark.range(rows).select(F.when(is_true, true).otherwise(false).alias("candidate"), F.when(is_true, before_true).otherwise(before_false).alias("before"), F.concat(F.lit(" "), w(26)).alias("after"), F.when(is_true, pick(["src/app", "config", "web", "crawl"], 27)).otherwise(pick(["src/app", "tests/unit", "docs", "web", "crawl", "go.sum"], 28)).alias("path"), is_true.cast("int").alias("label"))


# ------------------------------------------------------------------ forest


def _grow(x: np.ndarray, y: np.ndarray, depth: int, rng) -> tuple:
    share = float(y.mean())
    if depth == 0 or len(y) < 8 or share in (0.0, 1.0):
        return (share,)
    best = None
    for f in rng.choice(x.shape[1], max(2, int(np.sqrt(x.shape[1])) + 1), replace=False):
        order = np.argsort(x[:, f], kind="stable")
        v, t = x[order, f], y[order]
        cuts = np.flatnonzero(v[1:] > v[:-1]) + 1
        if not len(cuts):
            continue
        left = np.cumsum(t)[cuts - 1]
        p, q = left / cuts, (t.sum() - left) / (len(t) - cuts)
        impurity = cuts * p * (1 - p) + (len(t) - cuts) * q * (1 - q)
        i = int(impurity.argmin())
        if best is None or impurity[i] < best[0]:
            best = (impurity[i], int(f), float((v[cuts[i]] + v[cuts[i] - 1]) / 2))
    if best is None:
        return (share,)
    _, f, cut = best
    low = x[:, f] <= cut
    return (f, cut, _grow(x[low], y[low], depth - 1, rng), _grow(x[~low], y[~low], depth - 1, rng))


def fit_forest(x: np.ndarray, y: np.ndarray, params: ForestParams = ForestParams()) -> list[tuple]:
    rng = np.random.default_rng(params.seed)
    trees = []
    for _ in range(params.trees):
        at = rng.integers(len(y), size=len(y))
        trees.append(_grow(x[at], y[at], params.depth, rng))
    return trees


def forest_sql(trees: list[tuple]) -> str:
    """The forest's mean vote as one SQL expression over FEATURES."""

    def node(t: tuple) -> str:
        if len(t) == 1:
            return f"{t[0]!r}D"
        return f"CASE WHEN {FEATURES[t[0]]} <= {t[1]!r}D THEN {node(t[2])} ELSE {node(t[3])} END"

    return "(" + " + ".join(node(t) for t in trees) + f") / {len(trees)}.0D"


@dataclass(frozen=True)
class Judge:
    """What is learned: log odds of transitions, and the trees."""

    odds: list[float]
    trees: list[tuple]


def train(findings: DataFrame, params: ForestParams = ForestParams()) -> Judge:
    """Fit on labelled findings, the first ``params.findings`` by a hash of the candidate.

    Findings fall into two halves by another hash: one for the transitions, one
    for the trees, so that trees see transitions as new texts show them.
    """
    known = findings.where("label IS NOT NULL AND candidate IS NOT NULL")
    half = F.pmod(F.xxhash64("candidate", F.lit(1)), F.lit(2))
    odds = transition_odds(known.where(half == 0), params.findings)
    rows = features(known.where(half == 1), odds).orderBy(F.xxhash64("candidate", "before"), "candidate").limit(params.findings).select("label", *FEATURES).collect()
    return Judge(odds, fit_forest(np.array([r[1:] for r in rows], np.float64), np.array([r[0] for r in rows], np.float64), params))


# ------------------------------------------------------------------ scan


def candidates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path_col: str = "source") -> DataFrame:
    """(id, path, start, candidate, before, after) of every match, start in code points from 0."""
    text = F.col(text_col)
    hit = docs.where(text.isNotNull() & text.rlike(CANDIDATE)).select(F.col(id_col).alias("_id"), F.col(path_col).cast("string").alias("path"), F.xxhash64(text_col).alias("_row"), F.split(text, CANDIDATE, -1).alias("_between"), F.regexp_extract_all(text, F.lit(CANDIDATE), F.lit(0)).alias("_found"))
    each = hit.select("_id", "path", "_row", F.posexplode(F.arrays_zip("_between", F.concat("_found", F.array(F.lit(None).cast("string"))).alias("_found"), F.concat(F.slice("_between", 2, F.size("_between")), F.array(F.lit(None).cast("string"))).alias("_next"))).alias("_i", "p"))
    rows = each.select("_id", "path", "_row", "_i", F.col("p")["_found"].alias("candidate"), F.right(F.col("p")["_between"], F.lit(CONTEXT_CHARS)).alias("before"), F.left(F.col("p")["_next"], F.lit(CONTEXT_CHARS)).alias("after"), F.length(F.col("p")["_between"]).alias("_gap")).where("candidate IS NOT NULL").distinct()
    so_far = Window.partitionBy("_id", "_row", "path").orderBy("_i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    start = F.sum(F.col("_gap") + F.length("candidate")).over(so_far) - F.length("candidate")
    return rows.select(F.col("_id").alias(id_col), "path", start.alias("start"), "candidate", "before", "after")


def scan_secrets(docs: DataFrame, findings: DataFrame | None = None, params: ForestParams = ForestParams(), threshold: float = 0.5, id_col: str = "doc_id", text_col: str = "text", path_col: str = "source") -> DataFrame:
    """One row per candidate: id, start, length, candidate, score, is_secret.

    ``findings`` are labelled findings (candidate, before, after, path,
    label); without it those of ``labelled_findings`` are used. Null and empty
    texts have no candidates; rows that repeat id, text and path report each
    candidate once; null ids and paths are allowed. An empty table gives no
    rows. Extra columns are ignored.
    """
    judge = train(labelled_findings(docs.sparkSession) if findings is None else findings, params)
    scored = features(candidates(docs, id_col, text_col, path_col), judge.odds).withColumn("score", F.expr(forest_sql(judge.trees)))
    return scored.select(id_col, "start", F.length("candidate").cast("long").alias("length"), "candidate", "score", (F.col("score") >= threshold).alias("is_secret"))


def vote(trees: list[tuple], row: np.ndarray) -> float:
    """The forest's score of one feature row, in Python, for tests."""
    total = 0.0
    for t in trees:
        while len(t) > 1:
            t = t[2] if row[t[0]] <= t[1] else t[3]
        total += t[0]
    return total / len(trees)
