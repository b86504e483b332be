"""Secret scan: random-looking runs of characters, and a random forest that removes false positives.

All of it is DataFrame expressions: candidates and the text between them come from one pattern, each
candidate's features and the votes of the forest are array expressions, and no row is moved.  The forest
is fitted by Spark's own trainer on labelled findings: TRAINING_ROWS rows made from fixed forms by a
seeded generator, the only bound on a sample here; then its trees become CASE expressions.

Features: length, shares of digits and capitals, changes between character classes, distinct characters,
share covered by dictionary words, shares of vowels and of long runs of consonants, path signs in and around the candidate, words before it that name a
secret or something harmless, an assignment right before it or to it, a line of the same kind before it, and
the prefix of a known key form.  The text around a candidate includes its neighbours among the candidates.

Edge cases: a null text has no candidate and stays null; an empty text stays empty; repeated candidates
are found and judged each time; other columns are kept by `redacted_documents`, whatever their names; repeated
rows give repeated results; an empty table gives no rows.
"""

from __future__ import annotations

import json
import random
import re
import string

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import text_or_empty

MASK = "[SECRET]"
TRAINING_ROWS, TREES, DEPTH, SEED = 4000, 15, 6, 11
#: fixed values
NAMES_SECRET = r"(?i)(?:token|secret|passw|pwd|api.?key|access.?key|credential|bearer|private.?key|auth)"
NAMES_HARMLESS = r"(?i)(?:commit|sha\d|md5|hash|checksum|digest|uuid|guid|version|isbn|example|sample|dummy|order|invoice|phone|card|account|number|build|image|rev)"
KNOWN_FORM = r"^(?:AKIA|ASIA|ghp_|gho_|glpat-|sk-|sk_live|xox[abp]-|AIza|eyJ)"
ASSIGNED = r"[=:][ ]{0,2}[\"'`]?"
_NAMED = NAMES_SECRET.replace("(?i)(?:", "(?i:") + r"[^\n]{0,16}"
_TELLING = r"[A-Za-z_+/-]*+[0-9]", r"(?=[A-Z0-9_+/-]*+[a-z])[a-z0-9_+/-]*+[A-Z]", KNOWN_FORM[1:]
#: a run of 12 or more key characters with a digit, small and capital letters or a known prefix, or after an assignment or a name of a secret; with its padding, but not with the = of an assignment to it
CANDIDATE = rf"(?<![A-Za-z0-9_+/-])(?=[A-Za-z0-9_+/-]{{12}})(?:(?={'|'.join(_TELLING)})|(?<={ASSIGNED})|(?<={_NAMED}))[A-Za-z0-9_+/-]{{12,}}+(?:={{1,2}}(?!=|[\"'`]?[A-Za-z0-9_+/-]))?"
DICTIONARY = (
    "about access account after again also api article block book build call change check class code come commit company config content count "
    "country data date document download edition error example file final find first form from github group have here hello home host html http "
    "image index information item john key level life like line link list live local long main make media message model name network news none null "
    "number object only open option order other over page part path people place plan point post press private program project public report resource "
    "result sample search secret section server service setting site source start state string study system table template test text that their there "
    "they this time title token update upload user value version video view water week with word work world year your"
).split()
FEATURES = ("length", "digits", "capitals", "changes", "distinct", "dictionary", "paths", "names_secret", "names_harmless", "assigned", "known_form", "all_digits", "hexadecimal", "vowels", "hard", "assigns", "next_line")
_LOADED: dict[tuple, list] = {}


def features(candidate: Column, left: Column, right: Column) -> Column:
    """A struct of doubles; left and right are the text around the candidate."""
    n = F.char_length(candidate).cast("double")
    near, after = F.right(left, F.lit(32)), F.left(right, F.lit(8))
    count = lambda pattern: F.regexp_count(candidate, F.lit(pattern)).cast("double")
    has = lambda where, pattern: F.regexp_like(where, F.lit(pattern)).cast("double")
    kinds = r"[a-z](?=[^a-z])|[A-Z](?=[^A-Z])|[0-9](?=[^0-9])|[^A-Za-z0-9](?=[A-Za-z0-9])"
    words = "|".join(sorted(DICTIONARY, key=len, reverse=True))
    values = {
        "length": n,
        "digits": count("[0-9]") / n,
        "capitals": count("[A-Z]") / n,
        "changes": count(kinds) / n,
        "distinct": F.size(F.array_distinct(F.split(candidate, ""))).cast("double"),
        "dictionary": 1 - F.char_length(F.regexp_replace(F.lower(candidate), words, "")) / n,
        "paths": count("[/]") + has(near, r"[/\\.@]$") + has(after, r"^[.@/\\][A-Za-z0-9]"),
        "names_secret": has(near, NAMES_SECRET),
        "names_harmless": has(near, NAMES_HARMLESS),
        "assigned": has(near, ASSIGNED + "$"),
        "known_form": has(candidate, KNOWN_FORM),
        "all_digits": has(candidate, r"^[0-9_-]+$"),
        "hexadecimal": has(candidate, r"^[0-9a-f]+$"),
        "assigns": has(after, r"^[\"'`]?[ ]{0,2}(?:[+:?]?=|:)"),
        "next_line": has(near, r"[A-Za-z0-9_+/-]{20}\r?\n[ \t]{0,8}$"),
        "vowels": count("[AEIOUYaeiouy]") / n,
        "hard": 1 - F.char_length(F.regexp_replace(candidate, "(?i)[b-df-hj-np-tv-xz]{4,}", "")) / n,
    }
    return F.struct(*(values[x].alias(x) for x in FEATURES))


def is_candidate(left: str, candidate: str) -> bool:
    """Whether CANDIDATE takes the run `candidate` behind the text `left`."""
    if not re.fullmatch(r"[A-Za-z0-9_+/-]{12,}={0,2}", candidate):
        return False
    return bool(re.match("|".join(_TELLING), candidate) or re.search(f"(?:{ASSIGNED}|{_NAMED})$", left))


def labelled_findings(rows: int = TRAINING_ROWS, seed: int = SEED) -> list[tuple[str, str, str, int]]:
    """(left, candidate, right, label): secrets, and what looks like them, from fixed forms."""
    draw = random.Random(seed)
    run = lambda letters, n: "".join(draw.choices(letters, k=n))
    hexadecimal, mixed, capital = "0123456789abcdef", string.ascii_letters + string.digits, string.ascii_uppercase + string.digits
    prose = lambda: " ".join(run(string.ascii_lowercase, draw.randint(2, 9)) for _ in range(draw.randint(0, 5)))
    word = lambda: draw.choice(DICTIONARY)
    syllable = lambda: draw.choice("b c d f g l m n p r s t v br ch cl pr st tr th qu".split()) + draw.choice("a e i o u ea io".split()) + draw.choice(["", "", "n", "r", "s", "l", "t", "nt", "st", "ck"])
    spoken = lambda: "".join(syllable() for _ in range(draw.randint(4, 7)))
    drawn = lambda: draw.choice([word(), spoken()[: draw.randint(4, 9)]])

    def named() -> str:
        name = draw.choice(["token", "secret", "password", "passwd", "api_key", "apikey", "access_key", "auth_token", "client_secret", "private_key", "credential", "Token", "SECRET"])
        return f"{prose()} {name}{draw.choice([' = ', '=', ': ', ':', ' := ', ' '])}{draw.choice(['', chr(34), chr(39)])}"

    def setting() -> str:
        name = [draw.choice(["oauth2", "s3", "aws", "app1", "db2", "x509", "gcp", "prod3", "my"]), *draw.sample(["client", "access", "user", "api", "v2", "main"], draw.randint(0, 2)), draw.choice(["secret", "token", "api_key", "password", "secret_access_key", "private_key"])]
        return draw.choice([str.upper, str.lower])(draw.choice("__-").join(name))

    def secret() -> tuple[str, str]:
        form = draw.randrange(10)
        if form == 0:
            return named(), run(hexadecimal, draw.choice([16, 18, 20, 24, 32, 40, 64]))
        if form == 1:
            return draw.choice([named(), prose() + " "]), draw.choice(["AKIA", "ASIA"]) + run(capital, 16)
        if form == 2:
            return draw.choice([named(), prose() + " "]), draw.choice(["ghp_", "gho_", "sk-", "glpat-", "xoxb-", "AIza", "sk_live_"]) + run(mixed, draw.randint(20, 40))
        if form == 3:
            return named(), run(mixed + "+/", draw.randint(16, 64)) + draw.choice(["", "=", "=="])
        if form == 4:
            return named(), run(mixed + "_-", draw.randint(12, 24))
        if form == 5:
            return f"{prose()} Authorization: Bearer ", run(mixed + "_-", draw.randint(24, 64))
        if form == 6:  # no digit, or a late one
            letters = draw.choice([string.ascii_letters] * 3 + [string.ascii_lowercase, string.ascii_uppercase])
            return named(), run(letters, draw.randint(12, 48)) + draw.choice(["", run(string.digits, draw.randint(1, 3))])
        if form == 7:  # lines of a key
            return draw.choice(["BEGIN RSA PRIVATE KEY-----\n", "-----BEGIN PRIVATE KEY-----\n", *[run(mixed + "+/", 40) + "\n"] * 3]), run(mixed + "+/", draw.choice([64, 64, 64, draw.randint(12, 63)])) + draw.choice(["", "", "="])
        if form == 8:  # behind a name that is a candidate, or another secret
            return draw.choice([setting() + draw.choice(["=", "=\"", ": ", "\": \"", " = "]), f"{run(mixed, 14)} {named()}", f"{run(hexadecimal, 20)}\n{named()}"]), run(draw.choice([hexadecimal, mixed]), draw.choice([16, 20, 24, 32, 40]))
        return prose() + " ", run(mixed, draw.randint(32, 44))

    def harmless() -> tuple[str, str]:
        form = draw.randrange(17)
        if form == 0:
            return prose() + " ", run(string.digits, draw.choice([12, 13, 14, 15, 16, 16, 16, 18, 20]))
        if form == 1:
            return f"{prose()} {draw.choice(['commit', 'sha256', 'md5', 'checksum', 'hash', 'digest', 'rev'])}{draw.choice([' ', ': ', '=', ':'])}", run(hexadecimal, draw.choice([32, 40, 64]))
        if form == 2:
            return f"{prose()} {draw.choice(['id ', 'uuid ', 'uuid: ', ''])}", "-".join(run(hexadecimal, k) for k in (8, 4, 4, 4, 12))
        if form == 3:
            return f"{prose()} https://{word()}.com/", f"{word()}/{draw.randint(1990, 2030)}/{draw.randint(1, 12):02}/{word()}-{word()}-{word()}"
        if form == 4:
            return f"{prose()} /usr/", f"{word()}/{word()}{draw.randint(1, 99)}/{word()}"
        if form == 5:
            return prose() + " ", f"{word()}{draw.choice(['_', '-', ''])}{word()}{draw.randint(1, 2050)}{draw.choice(['_', '-', ''])}{word()}"
        if form == 6:
            return named(), draw.choice(["your_api_key_here_1", "example_token_123", "xxxxxxxxxxxx0000", "test_secret_value_1", "change_me_please_1", "000000000000", "123456789012", "sample-token-0001", "insert_token_here_2"])
        if form == 7:
            return prose() + " ", f"{draw.randint(1990, 2030)}-{draw.randint(1, 12):02}-{draw.randint(1, 28):02}T{draw.randint(0, 23):02}"
        if form == 8:
            return prose() + draw.choice([" +", " phone ", " "]), f"{draw.randint(1, 99)}-{run(string.digits, 3)}-{run(string.digits, 3)}-{run(string.digits, 4)}"
        if form == 9:
            return prose() + " base64,", run(mixed + "+/", draw.randint(200, 600))
        if form == 10:  # words after a colon or a name
            return draw.choice([named(), f"{prose()} {word()}{draw.choice([': ', ' = ', '=', ':'])}"]), draw.choice([spoken(), f"{drawn()}{draw.choice('_-')}{drawn()}", f"{word()}_{word()}_{word()}", f"{word()}/{word()}"])
        if form == 11:  # words with capitals
            return draw.choice([prose() + " ", prose() + ". ", named()]), draw.choice([spoken().capitalize(), f"{drawn().capitalize()}-{drawn().capitalize()}", spoken().capitalize() + "-" + drawn()])
        if form == 13:  # a name that is assigned to
            return draw.choice([prose() + "\n", "\n", prose() + " ", f"{run(hexadecimal, 24)}\n", f"{{ \"", f"{named()}{run(mixed, 20)}\n"]), setting()
        if form == 14:  # a hash or a number behind other candidates
            return f"{draw.choice([run(mixed, 16), setting(), run(hexadecimal, 32)])}{draw.choice([' ', ', ', chr(10)])}{draw.choice(['commit ', 'sha256: ', 'md5=', 'checksum ', 'order ', 'card '])}", draw.choice([run(hexadecimal, draw.choice([32, 40, 64])), run(string.digits, 16)])
        if form == 15:  # lines of an encoded file
            return run(mixed + "+/", 40) + "\n", run(mixed + "+/", 76)
        if form == 12:  # names in programs
            return draw.choice([prose() + " ", f"{prose()} {word()} = ", named(), f"{named()}{spoken()[:8]}; "]), draw.choice([drawn(), drawn().capitalize()]) + "".join(draw.choice([drawn(), drawn(), syllable()]).capitalize() for _ in range(draw.randint(1, 4)))
        return prose() + " ", run(string.ascii_lowercase, draw.randint(8, 20)) + run(string.digits, draw.randint(1, 3)) + run(string.ascii_lowercase, draw.randint(0, 8)) + run("abcdefgh", 4)

    out = []
    while len(out) < rows:
        label = len(out) % 2
        left, candidate = secret() if label else harmless()
        right = draw.choice([" ", '"', ". ", "' ", "\n"]) + prose()
        if candidate.lower().endswith(("secret", "token", "key", "password")):
            right = draw.choice(["=", " = ", ": ", "\": \"", ":", "=\""]) + run(hexadecimal, 20)
        if is_candidate(left, candidate):
            out.append((left, candidate, right, label))
    return out


def _tree(lines: list[str], at: int) -> tuple[object, int]:
    line = lines[at].strip()
    if line.startswith("Predict"):
        return float(line.split(":")[1]), at + 1
    feature, bound = re.match(r"If \(feature (\d+) <= ([-\d.E]+)\)", line).groups()
    low, at = _tree(lines, at + 1)
    high, at = _tree(lines, at + 1)
    return (int(feature), float(bound), low, high), at


def forest(spark: SparkSession, rows: int = TRAINING_ROWS, trees: int = TREES, depth: int = DEPTH, seed: int = SEED) -> list:
    """The fitted trees as nested (feature, bound, at most, above); fitted once per driver process."""
    key = (rows, trees, depth, seed)
    if key not in _LOADED:
        from pyspark.ml.classification import RandomForestClassifier
        from pyspark.ml.feature import VectorAssembler

        made = [dict(zip(("left", "candidate", "right", "label"), x)) for x in labelled_findings(rows, seed)]
        kind = "array<struct<left: string, candidate: string, right: string, label: int>>"
        frame = spark.range(1, numPartitions=1).select(F.inline(F.from_json(F.lit(json.dumps(made)), kind)))
        frame = frame.select(F.col("label").cast("double"), features(F.col("candidate"), F.col("left"), F.col("right")).alias("f")).select("label", "f.*")
        frame = VectorAssembler(inputCols=list(FEATURES), outputCol="features").transform(frame)
        fitted = RandomForestClassifier(numTrees=trees, maxDepth=depth, seed=seed, featureSubsetStrategy="sqrt").fit(frame)
        grown = []
        for tree in fitted.trees:
            grown.append(_tree(tree.toDebugString.strip().splitlines(), 1)[0])
        _LOADED[key] = grown
    return _LOADED[key]


def _votes(tree, values: Column) -> Column:
    if isinstance(tree, float):
        return F.lit(tree)
    feature, bound, low, high = tree
    return F.when(values[FEATURES[feature]] <= bound, _votes(low, values)).otherwise(_votes(high, values))


def forest_score(trees: list, values: Column) -> Column:
    """The share of trees that take a candidate with these features for a secret."""
    total = _votes(trees[0], values)
    for tree in trees[1:]:
        total = total + _votes(tree, values)
    return total / len(trees)


def scanned(documents: DataFrame, threshold: float = 0.5) -> DataFrame:
    """`row`, the columns of `documents`, with `text` and `findings`: every candidate in order, the text before it, its score, whether it is a secret; and `rest`, the text after the last."""
    trees = forest(documents.sparkSession)
    text = text_or_empty()
    marked = documents.select(F.struct("*").alias("row"), "text", F.regexp_extract_all(text, F.lit(f"({CANDIDATE})")).alias("candidates"), F.split(text, CANDIDATE, -1).alias("gaps"))
    # neighbours are text too: three candidates are longer than the text that features look at
    around = lambda some, size: F.concat_ws("", *(F.right(F.get(x, i), F.lit(size)) if size == 32 else F.left(F.get(x, i), F.lit(size)) for x, i in some))
    placed = F.transform(
        "candidates",
        lambda c, i: F.struct(
            c.alias("candidate"),
            F.get("gaps", i).alias("before"),
            around([("candidates", i - 3), ("gaps", i - 2), ("candidates", i - 2), ("gaps", i - 1), ("candidates", i - 1), ("gaps", i)], 32).alias("left"),
            around([("gaps", i + 1), ("candidates", i + 1)], 8).alias("right"),
        ),
    )
    judged = F.transform(placed, lambda x: F.struct(x["candidate"].alias("candidate"), x["before"].alias("before"), features(x["candidate"], x["left"], x["right"]).alias("values")))
    scored = F.transform(judged, lambda x: F.struct(x["candidate"].alias("candidate"), x["before"].alias("before"), forest_score(trees, x["values"]).alias("score")))
    findings = F.transform(scored, lambda x: F.struct(x["candidate"].alias("candidate"), x["before"].alias("before"), x["score"].alias("score"), (x["score"] > threshold).alias("secret")))
    return marked.withColumn("findings", findings).withColumn("rest", F.element_at("gaps", -1)).drop("candidates", "gaps")


def redacted_text() -> Column:
    """Of scanned rows: the text with MASK in place of each secret."""
    parts = F.transform("findings", lambda x: F.concat(x["before"], F.when(x["secret"], F.lit(MASK)).otherwise(x["candidate"])))
    return F.when(F.exists("findings", lambda x: x["secret"]), F.concat(F.array_join(parts, ""), F.col("rest"))).otherwise(F.col("text"))


def secret_report(documents: DataFrame) -> DataFrame:
    """doc_id, n_candidates, n_secrets, the secrets with their scores, and the redacted text."""
    found = scanned(documents.select("doc_id", "text"))
    secrets = F.filter("findings", lambda x: x["secret"])
    return found.select(
        "row.doc_id",
        F.size("findings").cast("long").alias("n_candidates"),
        F.size(secrets).cast("long").alias("n_secrets"),
        F.transform(secrets, lambda x: F.struct(x["candidate"].alias("candidate"), x["score"].alias("score"))).alias("secrets"),
        redacted_text().alias("redacted"),
    )


def redacted_documents(documents: DataFrame) -> DataFrame:
    """The documents with every secret masked; n_chars follows the text."""
    found = scanned(documents).select("row", redacted_text().alias("redacted"))
    length = F.coalesce(F.char_length("redacted").cast("long"), F.col("row.n_chars")) if "n_chars" in documents.columns else None
    new = {"text": F.col("redacted"), "n_chars": length}
    return found.select(*(new.get(c, F.col("row").getField(c)).alias(c) for c in documents.columns))
