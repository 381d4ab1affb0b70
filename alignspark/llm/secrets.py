"""Secret scanning: candidates by pattern, false positives removed by a random forest.

A candidate is a run of 16 or more characters that keys are written in, or a
value of 8 or more characters of any kind that is assigned to a key word
(``password = "k9Tq27!xLm"``), with the word it stands in and the words on both
sides. Features: length, how likely its character transitions are in running
text, runs of one character class, shares of digits, capitals and symbols,
distinct characters, dictionary coverage, an assignment or quotes around it, key
words, decoy words and prose before and after it, whether it is part of a path,
address or known identifier shape.

The forest is trained from labelled findings: made by rule (``findings``: known
formats and look-alikes, among words of the corpus) and found in all documents
where plain rules can label them (``field_findings``: provider formats are
secrets; letters or digits alone are not). The transitions and the dictionary's
words are counted over all documents, too. Findings of equal features, measured
in steps, are one row whose weight is their number; all found in the corpus
together weigh as much as those made at most. The forest is fitted
on one sorted partition of these, so it is the same whatever the cluster's shape, and
written out as expressions: scanning is one projection, without
join, shuffle or Python on the executors.

Null texts have no candidates; a candidate on which half of the trees agree is
none. Repeated candidates in a text are counted each and redacted everywhere,
longer ones first. Repeated rows are scanned alike. A very long text is scanned
whole, as one row. Empty tables give empty results, and a forest from made findings alone.
``redact`` keeps every other column of its input; its own two columns
(``_found``, ``_secrets``) replace input columns of these names.
"""

from __future__ import annotations

import math
import re
from typing import NamedTuple

from pyspark.ml.classification import RandomForestClassifier
from pyspark.ml.feature import VectorAssembler
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from alignspark.llm.common import WORD, constants, discard, stash, table

#: Trees and their depth; findings that are made; common words taken from the corpus; the mark that replaces a secret.
TREES, DEPTH, FINDINGS, COMMON, MARK = 15, 7, 8000, 300, "[SECRET]"
CANDIDATE = r"[A-Za-z0-9+/_\-]{16,}={0,2}"
#: What is assigned: a word without a name before it and without quotes and punctuation around it.
VALUE = r"^(?:[^\s=:\"'`]*[=:])?[\"'`(<\[]*([^\s\"'`<>()\[\]]{8,}?)[\"'`)>\],;.!?]*$"
#: Fixed word lists. Words of general English prose and of code, for the share of a candidate that they cover.
DICTIONARY = """
about account action active address after agent align allow alpha also amount analysis and apple array asset async author
back base batch before best block board body book bool bottom box branch build button byte cache call camel case cell chain change
char check child city class clean click client clock close cloud code color column comma common config connect content control
copy core count country create current custom data date day debug default delete design detail device dict direct display
document domain double down draft driver edit element else email empty enable engine entry error event every example export
extra factory false feature field file filter final find first flag float folder font for form format found from front full
function future game general global good graph green group guide handle hash head health hello help here high history home
host hour house icon ideal image import index info inner input insert install int internal into invoice item java join json
just key kind label lang large last layer layout left length level library light like limit line link list live load local
lock login long look loop machine mail main make manager map market master match max member memory menu message meta method
min mode model module month more mouse move name native network new next night node none normal not note null number object
office offset one only open option order other out output over page panel paper param parent parse part pass path pattern
people phone picture place plain player plugin point policy pool port post power press price print private process product
profile program project public python query queue quick quote random range rate read ready record red region release remote
remove report request reset resource response result return right role room root route row rule run safe sale same sample
save scale schema school scope script search second section secure select send series server service session set share
sheet shop short show side sign simple single site size small social sort source space split stack staff standard start state
static status step still stock stop storage store stream street string strong style submit success sum support switch system
table tag target task team template term test text that the their then there thing this thread time title token tool top
total track train tree true trust type under union unit update upper url use user util value vector version video view
virtual visit void wait watch water web week white wide will window with word work world write year yellow zone
tion ing ent ers ion ati ter the and for her hat ere his ble nte con men res pro
""".split()
KEYWORDS = r"(secret|token|passw|pwd|api.?key|auth|bearer|credential|private|access.?key|signature|client.?id)"
DECOYS = r"(commit|sha1|sha256|md5|digest|checksum|uuid|guid|revision|etag|integrity|example|placeholder|sample|dummy|your)"
#: Formats that providers give their keys (fixed values).
FORMATS = r"^(A[KS]IA[A-Z0-9]{16}|gh[pousr]_[A-Za-z0-9]{30,}|xox[abp]-[A-Za-z0-9-]{20,}|[sr]k_(live|test)_[A-Za-z0-9]{20,}|glpat-[A-Za-z0-9_-]{20,})$"
ASSIGNED = r"(?i)" + KEYWORDS + r"\w*[\"'`\]]?\s*(=|:|:=|=>)\s*\S+$"
FEATURES = [
    "length", "transitions", "runs", "digits", "capitals", "symbols", "distinct", "covered", "vowels", "assigned", "quoted", "keyword",
    "keyword_after", "decoy", "decoy_after", "prose_before", "prose_after", "path", "uuid", "hex", "repeated",
]
#: Steps in which features are measured for training, a part of one: equal findings become one row.
STEPS = {"transitions": 8, "runs": 32, "digits": 32, "capitals": 32, "symbols": 32, "covered": 32, "vowels": 32}

# --- what the corpus says about plain text -------------------------------------------------------------------------------

#: Character classes of the transitions: other, the letters, digits.
CLASSES, LETTERS = 28, "abcdefghijklmnopqrstuvwxyz0123456789"


class Style(NamedTuple):
    """Plain text: its commonest words, and log2 of each transition's probability (CLASSES x CLASSES)."""

    words: list[str]
    transitions: list[float]


def _classes(text: Column) -> Column:
    """The class of every character of a text."""
    return F.transform(F.split(F.lower(text), ""), lambda c: F.least(F.call_function("instr", F.lit(LETTERS), c), F.lit(CLASSES - 1)))


def _style(words: list[str], pairs: dict[int, int]) -> Style:
    """Counts of transitions (keyed first class * CLASSES + second) and the fixed word list's own, smoothed by one."""
    counts = [1 + pairs.get(k, 0) for k in range(CLASSES * CLASSES)]
    for word in DICTIONARY:
        numbers = [LETTERS.index(c) + 1 for c in word]
        for a, b in zip(numbers, numbers[1:]):
            counts[a * CLASSES + b] += 1
    table_ = []
    for a in range(CLASSES):
        row = counts[a * CLASSES : (a + 1) * CLASSES]
        table_ += [round(math.log2(n / sum(row)), 6) for n in row]
    return Style(words, table_)


def learn(texts: DataFrame) -> Style:
    """Common words and transitions of all texts."""
    words = texts.select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}0-9]+"), F.lit(0))).alias("w")).groupBy("w").agg(F.count("*").alias("n"))
    words = stash(words, "secret-words")
    common = words.where(r"w RLIKE '^\\p{L}{3,}$'").orderBy(F.desc("n"), "w").limit(COMMON).collect()
    steps = words.select("n", _classes(F.col("w")).alias("c")).select("n", F.explode(F.transform(F.slice("c", 1, F.greatest(F.size("c") - 1, F.lit(0))), lambda a, i: a * CLASSES + F.get("c", i + 1))).alias("k"))
    style = _style([r.w for r in common], {r.k: r.n for r in steps.groupBy("k").agg(F.sum("n").alias("n")).collect()})
    discard(words)
    return style


# --- candidates and their features ---------------------------------------------------------------------------------------


def _share(text: Column, pattern: str) -> Column:
    """Part of a text that is left once what matches is taken out."""
    return F.length(F.regexp_replace(text, pattern, "")) / F.greatest(F.length(text), F.lit(1))


def features(c: Column, style: Style) -> Column:
    """The features of a candidate struct (token, word, left, right, before, after) as a struct of doubles."""
    token, word = c["token"], c["word"]
    near = F.concat_ws(" ", F.array_join(c["before"], " "), c["left"])
    past = F.concat_ws(" ", c["right"], F.array_join(c["after"], " "))
    known = sorted({w for w in DICTIONARY if len(w) >= 3} | {w for w in style.words if w.isalpha()}, key=lambda w: (-len(w), w))
    table_ = constants(style.transitions)
    # the mean over neighbouring characters, which are bound to a name by a one-element array
    steps = lambda k: F.aggregate(F.slice(k, 2, F.greatest(F.size(k) - 1, F.lit(0))), F.struct(F.get(k, F.lit(0)).alias("a"), F.lit(0.0).alias("s")),
                                  lambda acc, b: F.struct(b.alias("a"), (acc["s"] + F.get(table_, acc["a"] * CLASSES + b)).alias("s")))["s"] / F.greatest(F.size(k) - 1, F.lit(1))
    # no repeated groups in these patterns: Java's matcher recurses for each repetition, and words can be very long
    prose = r"^[\"'`(]*\p{L}[\p{L}\-'\u2019]*\p{P}*$"
    number = lambda flag: flag.cast("double")
    values = {
        "length": F.length(token).cast("double"),
        "transitions": F.get(F.transform(F.array(_classes(token)), steps), F.lit(0)),
        "runs": F.length(F.regexp_replace(token, "([a-z]+|[A-Z]+|[0-9]+|[^A-Za-z0-9]+)", "x")) / F.length(token),
        "digits": F.lit(1.0) - _share(token, "[0-9]+"),
        "capitals": F.lit(1.0) - _share(token, "[A-Z]+"),
        "symbols": _share(token, "[A-Za-z0-9]+"),
        "distinct": F.size(F.array_distinct(F.split(token, ""))).cast("double"),
        "covered": F.lit(1.0) - _share(F.lower(token), "(" + "|".join(known) + ")"),
        "vowels": F.lit(1.0) - _share(F.lower(token), "[aeiouy]+"),
        "assigned": number(near.rlike(r"[=:]>?\s*[\"'`(<\[]*$")),
        "quoted": number(c["left"].rlike("[\"'`]$") & c["right"].rlike("^[\"'`]")),
        "keyword": number(near.rlike("(?i)" + KEYWORDS)),
        "keyword_after": number(past.rlike("(?i)" + KEYWORDS)),
        "decoy": number(F.concat_ws(" ", near, token).rlike("(?i)" + DECOYS)),
        "decoy_after": number(past.rlike("(?i)" + DECOYS)),
        "prose_before": number(F.coalesce(F.get(c["before"], F.size(c["before"]) - 1), F.lit("")).rlike(prose)),
        "prose_after": number(F.coalesce(F.get(c["after"], F.lit(0)), F.lit("")).rlike(prose)),
        "path": number(word.rlike(r"(://|^[./~]|\.[a-z]{2,4}\b|@)") | token.rlike(r"^[^0-9]*/[^0-9]*/")),
        "uuid": number(token.rlike(r"^[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}$")),
        "hex": number(token.rlike(r"^([0-9a-f]+|[0-9A-F]+)$")),
        "repeated": number(token.rlike(r"(.)\1{4}") | token.rlike(r"^(.{1,4})\1{2}")),
    }
    return F.struct(*[F.coalesce(values[n], F.lit(0.0)).alias(n) for n in FEATURES])


def candidates(text: Column) -> Column:
    """Array of (token, word, left, right, before, after) of a text: what stands around the token in its word, and the words beside it."""
    words = F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))

    def of_words(w: Column) -> Column:
        def possible(p: Column) -> Column:
            x, before = p["x"], F.coalesce(F.get(w, p["i"] - 1), F.lit(""))
            named = F.contains(x, F.lit("=")) | F.contains(x, F.lit(":")) | F.endswith(before, F.lit("=")) | F.endswith(before, F.lit(":")) | F.endswith(before, F.lit("=>"))
            return (F.length(x) >= 16) | ((F.length(x) >= 8) & named)

        places = F.filter(F.transform(w, lambda x, i: F.struct(x.alias("x"), i.alias("i"))), possible)

        def of_place(p: Column) -> Column:
            x, i = p["x"], p["i"]
            before = F.slice(w, F.greatest(i - 2, F.lit(1)), F.least(i, F.lit(3)))
            after = F.slice(w, i + 2, 2)
            runs = F.regexp_extract_all(x, F.lit(CANDIDATE), F.lit(0))
            given = F.concat_ws(" ", F.array_join(before, " "), x).rlike(ASSIGNED)
            value = F.when(given, F.regexp_extract(x, VALUE, 1)).otherwise("")
            tokens = F.when((value != "") & ~F.array_contains(runs, value), F.array_append(runs, value)).otherwise(runs)
            part = lambda t, k: F.call_function("substring_index", x, t, F.lit(k))
            return F.transform(tokens, lambda t: F.struct(
                t.alias("token"), x.alias("word"), part(t, 1).alias("left"), part(t, -1).alias("right"), before.alias("before"), after.alias("after")))

        return F.flatten(F.transform(places, of_place))

    # one-element array as a binding: the words are made once
    return F.flatten(F.transform(F.array(words), of_words))


# --- labelled findings ----------------------------------------------------------------------------------------------


def findings(spark: SparkSession, n: int = FINDINGS, style: Style | None = None, first: int = 0) -> DataFrame:
    """Labelled findings: a line of text around each, and whether it is a secret. Made by rule, the same every time."""
    h = lambda tag: F.sha2(F.concat(F.lit(tag), F.col("id").cast("string")), 512)
    b62 = lambda tag: F.translate(F.base64(F.unhex(h(tag))), "+/=\r\n", "xYz")
    b64 = lambda tag: F.translate(F.base64(F.unhex(h(tag))), "\r\n", "")
    pick = lambda tag, options: F.get(F.split(F.lit("\n".join(options)), "\n"), F.pmod(F.xxhash64("id", F.lit(tag)), F.lit(len(options))).cast("int"))
    words = [w for w in DICTIONARY if len(w) > 3]
    word = lambda tag: pick(tag, words)
    text_words = words + (style.words if style else [])
    name = lambda tag: pick(tag, ["token", "secret", "api_key", "apikey", "password", "auth_token", "access_key", "client_secret", "TOKEN", "SECRET_KEY"])
    tie = lambda tag: pick(tag, [" = \"", "=\"", ": \"", ": '", " = '", "=", ": ", " = "])
    size = lambda tag, lo, hi: F.pmod(F.xxhash64("id", F.lit(tag)), F.lit(hi - lo)) .cast("int") + lo
    prose = lambda tag: F.concat_ws(" ", *[pick(f"{tag}{i}", text_words) for i in range(4)])
    hexed = F.substring(h("a"), F.lit(1), size("hx", 32, 64))
    long_word = F.concat(*[pick(f"l{i}", text_words) for i in range(4)])
    camel = F.concat(word("c0"), F.initcap(word("c1")), F.initcap(word("c2")), F.initcap(word("c3")))
    snake = F.concat_ws("_", *[word(f"s{i}") for i in range(4)])
    uuid = F.concat_ws("-", *[F.substring(h("u"), a, b) for a, b in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))])
    short = F.substring(b62("v"), F.lit(1), size("vx", 9, 16))
    marked = F.concat(F.substring(b62("y"), F.lit(1), size("y0", 4, 8)), pick("y1", ["!", "@", "#", "$", ".", "%", "&"]), F.substring(b62("y2"), F.lit(1), size("y3", 4, 9)))
    lines = [
        (1, F.concat(name("n"), tie("t"), hexed, F.lit('"'))),
        (1, F.concat(name("n"), tie("t"), F.substring(b62("b"), F.lit(1), size("bx", 20, 60)), F.lit('"'))),
        (1, F.concat(F.lit("AKIA"), F.upper(F.substring(b62("k"), 1, 16)))),
        (1, F.concat(pick("p", ["ghp_", "gho_", "xoxb-", "sk_live_", "glpat-"]), F.substring(b62("g"), 1, 36))),
        (1, F.concat(F.lit("Authorization: Bearer "), F.substring(b62("j"), 1, 40))),
        (1, F.concat(name("n"), F.lit(" = "), F.upper(hexed), F.lit(" "))),
        (1, F.concat(F.lit("PRIVATE KEY "), F.substring(b64("m"), 1, 64))),
        (1, F.concat(name("n"), tie("t"), short, F.lit('"'))),
        (1, F.concat(name("n"), tie("t"), marked, F.lit('"'))),
        (1, F.concat(name("n"), tie("t"), F.substring(b62("d0"), 1, 20), F.lit("."), F.substring(b62("d1"), 1, 30), F.lit('"'))),
        (0, F.concat(prose("q"), F.lit(" "), long_word)),
        (0, F.concat(word("w"), F.lit(" = "), camel)),
        (0, F.concat(word("w"), F.lit("("), snake, F.lit(")"))),
        (0, F.concat(F.lit("/"), F.concat_ws("/", *[word(f"d{i}") for i in range(5)]))),
        (0, F.concat(F.lit("id: "), uuid)),
        (0, F.concat(F.lit("commit "), F.substring(h("e"), 1, 40))),
        (0, F.concat(pick("dg", ["sha256: ", "checksum = ", "md5 ", "integrity="]), F.substring(h("f"), F.lit(1), size("fx", 32, 64)))),
        (0, F.concat(name("n"), tie("t"), pick("ph", ["your_api_key_here", "xxxxxxxxxxxxxxxxxxxxxxxx", "example_secret_token", "placeholder_password", "xxxxxxxxxx", "example123", "your-token"]), F.lit('"'))),
        (0, F.concat(prose("q"), F.lit(" "), F.translate(F.substring(h("z"), 1, 16), "abcdef", "012345"))),
        (0, F.concat(F.lit("https://example.com/"), F.concat_ws("/", word("h1"), snake))),
        (0, F.concat(prose("q"), F.lit(" "), F.initcap(long_word), F.lit(", "), long_word, F.lit("."))),
        (0, F.concat(name("n"), F.lit(" "), prose("q"), F.lit(" "), long_word)),
        (0, F.concat(F.lit("----------------------------------"))),
        (0, F.concat(F.upper(prose("q")), F.lit(" "), F.upper(long_word), F.lit("!! "))),
        (0, F.concat(prose("q"), F.lit(" "), F.repeat(word("r"), 4))),
        (0, F.concat(name("n"), F.lit(": "), F.concat(pick("m0", text_words), pick("m1", text_words)), F.lit(" "), prose("q"))),
        (0, F.concat(name("n"), F.lit(" = "), word("g0"), F.lit("."), word("g1"), F.initcap(word("g2")), pick("g3", ["()", "", ".value", ";"]))),
        (0, F.concat(name("n"), F.lit(" = "), word("g0"), F.initcap(word("g1")), F.initcap(word("g2")))),
        (0, F.concat(name("n"), tie("t"), F.concat_ws("_", word("k0"), word("k1")), F.lit('"'))),
        (0, F.concat(name("n"), F.lit(": 20"), F.substring(F.translate(h("o"), "abcdef", "012345"), 1, 2), F.lit("-0"), F.lit("4-1"), F.lit("7"))),
    ]
    kind = F.col("id") % len(lines)
    label, text = F.lit(None), F.lit(None)
    for k, (is_secret, line) in reversed([*enumerate(lines)]):
        label, text = F.when(kind == k, is_secret).otherwise(label), F.when(kind == k, line).otherwise(text)
    return spark.range(first, first + n).select("id", label.cast("double").alias("label"), F.concat(prose("x"), F.lit(" "), text, F.lit(" "), prose("y")).alias("text"))


def field_findings(texts: DataFrame) -> DataFrame:
    """(label, c): candidates of documents that plain rules can label; others are left out."""
    found = texts.select(F.explode(candidates(F.col("text"))).alias("c"))
    token = F.col("c.token")
    label = F.when(token.rlike(FORMATS), 1.0).when(token.rlike(r"^[\p{L}\-_/']+[.,;:]*$") | token.rlike(r"^[0-9.,:/-]+$"), 0.0)
    return found.select(label.alias("label"), "c").where("label IS NOT NULL")


class Scanner(NamedTuple):
    """A fitted forest with the style of plain text that its features use."""

    forest: object
    style: Style


def _stepped(f: Column) -> Column:
    """Features in steps: shares and transitions rounded, lengths over 64 to sixteens and up to 1024."""
    values = {n: f[n] for n in FEATURES} | {n: F.round(f[n] * k) / k for n, k in STEPS.items()}
    for n in ("length", "distinct"):
        values[n] = F.when(f[n] > 64, F.round(F.least(f[n], F.lit(1024.0)) / 16) * 16).otherwise(f[n])
    return F.struct(*[values[n].alias(n) for n in FEATURES])


def train(labelled: DataFrame, style: Style | None = None, texts: DataFrame | None = None) -> Scanner:
    """The forest, fitted on the candidates of labelled lines (label, text) and on what rules can label in ``texts``."""
    style = style or _style([], {})
    lines = stash(labelled.select("label", "text"), "secret-lines")  # so that no plan below holds how they are made
    rows = lines.select("label", F.explode(candidates(F.col("text"))).alias("c"), F.lit(0).alias("seen"))
    if texts is not None:
        rows = rows.unionByName(field_findings(texts).withColumn("seen", F.lit(1)))
    rows = rows.select("label", "seen", features(F.col("c"), style).alias("f")).select("label", "seen", _stepped(F.col("f")).alias("f")).select("label", "seen", "f.*")
    kinds = stash(rows.groupBy("label", *FEATURES).agg(F.count("*").alias("n"), F.sum("seen").alias("seen")), "secret-findings")
    found, n_kinds = kinds.agg(F.sum("seen"), F.count("*")).first()
    weight = F.col("n") - F.col("seen") + F.col("seen") * min(1.0, FINDINGS / max(1, found or 0))
    # bagging and splits depend on the order and partitions of the rows: one sorted partition
    rows = kinds.withColumn("weight", weight).repartition(1).sortWithinPartitions("label", *FEATURES)
    ready = VectorAssembler(inputCols=FEATURES, outputCol="features").transform(rows).select("label", "features", "weight")
    # as many bins as let the learner take its thresholds from all rows: it samples when rows exceed their square
    bins = max(128, math.isqrt(n_kinds) + 1)
    learner = RandomForestClassifier(numTrees=TREES, maxDepth=DEPTH, seed=7, featureSubsetStrategy="sqrt", cacheNodeIds=False, weightCol="weight", maxBins=bins)
    scanner = Scanner(learner.fit(ready), style)
    discard(lines, kinds)
    return scanner


def fit(docs: DataFrame) -> Scanner:
    """A scanner for a corpus: made findings among its words, and what rules can label in all of it."""
    texts = docs.where("text IS NOT NULL").select("text")
    style = learn(texts)
    return train(findings(docs.sparkSession, style=style), style, texts)


def share_of(model, f: Column) -> Column:
    """The share of trees that call a feature struct a secret: constant arrays hold the nodes, a walk for each tree.

    A node's left child follows it. A leaf has feature -1 and its verdict for a threshold.
    """
    roots, open_ = [], []
    feature, threshold, right = [], [], []
    for line in model.toDebugString.splitlines():
        text = line.strip()
        if text.startswith("Tree "):
            roots.append(len(feature))
        elif m := re.match(r"If \(feature (\d+) <= ([-\d.Ee]+)\)", text):
            open_.append(len(feature))
            feature.append(int(m[1]))
            threshold.append(float(m[2]))
            right.append(-1)
        elif text.startswith("Else"):
            right[open_.pop()] = len(feature)
        elif m := re.match(r"Predict: ([\d.]+)", text):
            feature.append(-1)
            threshold.append(1.0 if float(m[1]) > 0.5 else 0.0)
            right.append(-1)
    of, limit, other = constants(feature, "int"), constants(threshold), constants(right, "int")

    def walk(values: Column) -> Column:
        step = lambda n, _: F.when(F.get(of, n) < 0, n).when(F.get(values, F.get(of, n)) <= F.get(limit, n), n + 1).otherwise(F.get(other, n))
        return F.aggregate(constants(roots, "int"), F.lit(0.0), lambda votes, root: votes + F.get(limit, F.aggregate(constants([0] * DEPTH, "int"), root, step)))

    # a one-element array binds the features to a name
    return F.get(F.transform(F.array(F.array(*[f[n] for n in FEATURES])), walk), F.lit(0)) / len(roots)


def scan(docs: DataFrame, model: Scanner) -> DataFrame:
    """Adds ``_found`` (features and token of every candidate) and ``_secrets`` (tokens that more than half of the trees hold secret)."""
    found = F.transform(candidates(F.col("text")), lambda c: F.struct(c["token"].alias("token"), features(c, model.style).alias("f")))
    secret = F.transform(F.filter("_found", lambda c: share_of(model.forest, c["f"]) > 0.5), lambda c: c["token"])
    return docs.withColumn("_found", found).withColumn("_secrets", secret)


def redact(docs: DataFrame, model: Scanner) -> DataFrame:
    """``docs`` with every secret in ``text`` replaced by the mark; longer secrets first. Other columns stay."""
    marked = scan(docs, model)
    longest = F.array_sort(F.array_distinct("_secrets"), lambda a, b: F.when(F.length(a) != F.length(b), F.length(b) - F.length(a)).when(a < b, -1).when(a > b, 1).otherwise(0))
    clean = F.when(F.size("_secrets") == 0, F.col("text")).otherwise(
        F.aggregate(longest, F.col("text"), lambda text, s: F.replace(text, s, F.lit(MARK)))
    )
    return marked.withColumn("text", clean)


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document scanned: candidates, secrets, and digests of the secrets and of the redacted text."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return redact(docs, fit(docs)).select(
        "doc_id", F.size("_found").cast("long").alias("n_candidates"), F.size("_secrets").cast("long").alias("n_secrets"),
        F.transform("_secrets", lambda s: F.sha2(s, 256)).alias("secret_sha256"),
        F.sha2(F.coalesce(F.col("text"), F.lit("")), 256).alias("redacted_sha256"),
    )
