r"""Secret scans: proposed strings, and a random forest that removes false positives.

One pattern proposes private keys with their lines, any value of eight characters or more that is
assigned to a name with a credential word in it, whatever symbols it holds, long unbroken strings,
and shorter ones behind an assignment.  Each gets features of length, character transitions,
dictionary coverage, path and neighbouring words, and a forest grown from labelled findings scores
it.  The dictionary is learned from the corpus: the ``WORDS`` words that most documents hold,
counted over all of them.  Scanning is DataFrame expressions only: the trees are constant tables
walked by higher-order functions.  The labelled findings are a bounded table (``FINDINGS`` rows,
made from public formats and the dictionary's words with a fixed seed, unless others are given);
their features come from the same expressions.

Defined cases: a null text is empty, a null path an empty string; repeated ids and rows each give
their findings; texts without findings give no row; offsets are code points, end exclusive; very
long runs are one proposal; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import random
import string
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from aggclust.llm import forest
from aggclust.llm.batches import documents

THRESHOLD, NEAR, FINDINGS, SEED, WORDS = 0.5, 40, 4000, 5, 1500
_NAME = r"""(?:pass(?:word|wd|phrase)?|pwd|secret|token|api[_-]?key|access[_-]?key|auth|credential)"""
#: A name with a credential word in it, and what assigns a value to it.
PREFIX = rf"""(?<![A-Za-z0-9_-])[A-Za-z0-9_-]{{0,30}}?(?i:{_NAME})[A-Za-z0-9_-]{{0,12}}["']?[ \t]{{0,3}}(?:=>|:=|=|:)[ \t]{{0,3}}["']?"""
_VALUE = r"""[^\s"'`,;<>()\[\]{}]{7,}[^\s"'`,;<>()\[\]{}.]"""
_KEY = r"""-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----[A-Za-z0-9+/=\s:,.-]+?-----END [A-Z ]{0,20}PRIVATE KEY-----"""
_RUN = r"""(?<![A-Za-z0-9_+/-])[A-Za-z0-9_+/-]{16,}+={0,2}|(?:(?<=[=:])|(?<=[=:]["' ])|(?<=[=:] ["']))[A-Za-z0-9_+/-]{8,}+={0,2}"""
CANDIDATE = f"{_KEY}|{PREFIX}{_VALUE}|{_RUN}"
# Words and syllables of ordinary text and of identifiers, beside those of the corpus.
DICTIONARY = (
    "the and ing tion ment heit keit lich ung sch ein ver ent able ness less ation ous con pre pro per est ers ght ould"
    " with from that this have which there their about other name value key test user data file path index config example"
    " sample token secret password admin server client service class function return import public private static final"
    " string number array object default error message request response header content length version update create"
    " delete insert select table column where order group count ción que ado ido mente eau eux elle ais ont ent ère tre"
    " der die das und ist nicht ach och auf zu be er en es an on in at st nd th re ti or le de te ou ea wh ly sh ha he"
).split()
# Openings of tokens that their issuers publish.
KINDS = {"aws_key": "(AKIA|ASIA)[A-Z0-9]{16}", "github_token": "gh[pousr]_", "slack_token": "xox[abprs]-", "google_key": "AIza", "stripe_key": "[sr]k_(live|test)_", "gitlab_token": "glpat-", "jwt": "eyJ[A-Za-z0-9_-]+", "private_key": "-----BEGIN"}
ASSIGNED = rf"""(?i){_NAME}[a-z0-9_-]*["']?\s*(=>|:=|=|:)\s*["']?$"""

_FROM = string.ascii_uppercase + string.ascii_lowercase + string.digits
_TO = "U" * 26 + "L" * 26 + "D" * 10


def _q(text: str) -> str:
    return 'r"' + text.replace('"', r"\x22") + '"'


def _either(words: list[str]) -> str:
    """A pattern of the longest of ``words`` at a place, factored by common beginnings."""
    tree: dict = {}
    for w in words:
        at = tree
        for c in w:
            at = at.setdefault(c, {})
        at[""] = {}

    def pattern(at: dict) -> str:
        inner = [c + pattern(below) for c, below in sorted(at.items()) if c]
        if not inner:
            return ""
        return f"(?:{'|'.join(inner)})" + ("?" if "" in at else "")

    return pattern(tree)


def features(words: tuple[str, ...]) -> dict[str, str]:
    """name -> SQL over value v, the text before b, behind a, and the path p."""
    long = _either([w for w in words if len(w) > 2])
    short = _either([w for w in words if len(w) == 2])
    return {
        "f_length": "double(length(v))",
        "f_transitions": f"(length(regexp_replace(translate(v, '{_FROM}', '{_TO}'), r'(.)\\1+', '$1')) - 1D) / greatest(1, length(v) - 1)",
        "f_dictionary": f"1D - length(regexp_replace(regexp_replace(lower(v), '{long}', ''), '{short}', '')) / double(length(v))",
        "f_digits": "length(regexp_replace(v, '[^0-9]', '')) / double(length(v))",
        "f_upper": "length(regexp_replace(v, '[^A-Z]', '')) / double(length(v))",
        "f_symbols": "length(regexp_replace(v, '[A-Za-z0-9]', '')) / double(length(v))",
        "f_distinct": "size(array_distinct(split(v, ''))) / double(length(v))",
        "f_hex": "double(v RLIKE '^([0-9a-f]+|[0-9A-F]+)$')",
        "f_letters": "double(v RLIKE '^[A-Za-z]+$')",
        "f_issuer": f"double(v RLIKE '^({'|'.join(KINDS.values())})')",
        "f_assigned": f"double(b RLIKE {_q(ASSIGNED)})",
        "f_near": "double(lower(concat(b, ' ', a)) RLIKE 'pass|secret|token|key|credential|auth')",
        "f_fake": "double(lower(concat(b, ' ', v, ' ', a)) RLIKE 'example|sample|dummy|fake|placeholder|your|changeme|xxxx|sha256|md5|commit|checksum')",
        "f_path": "double(lower(p) RLIKE 'test|example|fixture|mock|doc/|sample')",
    }


def learn_dictionary(docs: DataFrame, size: int = WORDS, text_col: str = "text") -> tuple[str, ...]:
    """The words of 2 to 16 letters that most documents hold, counted over all documents; ties by the word."""
    words = F.array_distinct(F.split(F.lower(F.coalesce(F.col(text_col).cast("string"), F.lit(""))), r"[^a-z\u00e0-\u024f]+"))
    per = docs.select(F.explode(words).alias("word")).where(F.length("word").between(2, 16)).groupBy("word").agg(F.count("*").alias("n"))
    return tuple(r["word"] for r in per.orderBy(F.desc("n"), "word").limit(size).collect())


def candidates(texts: DataFrame, keep: list[str]) -> DataFrame:
    """Rows of ``texts`` (``_t``, ``_p`` and ``keep``) per proposed string: start, v, b, a, p."""
    parts = f"array(named_struct('o', split(_t, {_q(CANDIDATE)}, -1), 'm', regexp_extract_all(_t, {_q(CANDIDATE)}, 0)))"
    none = "CAST(array() AS array<struct<start:int,v:string,b:string,a:string>>)"
    # What a match has before its value belongs to the text before it.
    value = f"regexp_replace(x.m, {_q('^' + PREFIX)}, '')"
    item = (
        f"element_at(transform(array({value}), v -> named_struct('start', c.at + length(x.o) + length(x.m) - length(v), 'v', v, "
        f"'b', right(concat(right(x.o, {NEAR}), left(x.m, length(x.m) - length(v))), {NEAR}), 'a', left(x.`2`, {NEAR}))), 1)"
    )
    walked = (
        f"aggregate(arrays_zip(z.o, z.m, slice(z.o, 2, size(z.o))), named_struct('at', 0, 'found', {none}), (c, x) -> "
        f"named_struct('at', c.at + length(x.o) + coalesce(length(x.m), 0), 'found', CASE WHEN x.m IS NULL THEN c.found ELSE array_append(c.found, {item}) END), c -> c.found)"
    )
    found = F.expr(f"element_at(transform({parts}, z -> {walked}), 1)")
    return texts.select(*keep, F.col("_p").alias("p"), F.explode(found).alias("_c")).select(*keep, "p", "_c.*").where("length(v) >= 8")


def with_features(found: DataFrame, words: tuple[str, ...]) -> DataFrame:
    return found.select("*", *(F.expr(e).alias(n) for n, e in features(words).items()))


def labelled_findings(n: int = FINDINGS, seed: int = SEED, words: tuple[str, ...] = tuple(DICTIONARY)) -> list[tuple[str, str, int]]:
    """(text, path, label) around one string each: secrets by public formats, and what is mistaken for them."""
    r = random.Random(seed)
    long = [w for w in words if len(w) >= 8] or ["something"]
    # Words around the string stay too short to be proposed themselves.
    word = lambda k=1: " ".join("".join(r.choice(words) for _ in range(r.randint(1, 2)))[:12] for _ in range(k))
    chars = lambda alphabet, k: "".join(r.choice(alphabet) for _ in range(k))
    hexa, alnum, upper = "0123456789abcdef", string.ascii_letters + string.digits, string.ascii_uppercase + string.digits
    base64, marks = alnum + "+/", "!@#$%^&*-_.+?~"
    names = ("password", "passwd", "secret", "token", "api_key", "apikey", "access_key", "auth_token", "client_secret", "DB_PASSWORD", "pwd", "my_service_token")
    joins = ("=", " = ", ": ", "=\"", " = \"", ": '", "=>\"", " => \"", ":=", " := '", ":")

    def password() -> str:
        """A word or letters with digits and marks, as people choose them, or drawn at random."""
        if r.random() < 0.5:
            return chars(alnum + marks, r.randint(9, 24))
        made = list(r.choice(words).title() + r.choice(words) + chars(string.digits, r.randint(1, 4)) + chars(marks, r.randint(1, 3)))
        swap = {"a": "@", "o": "0", "e": "3", "i": "1", "s": "$"}
        return "".join(swap.get(c, c) if r.random() < 0.6 else c for c in made).ljust(8, "9")

    real = [
        lambda: "AKIA" + chars(upper, 16),
        lambda: "ASIA" + chars(upper, 16),
        lambda: "ghp_" + chars(alnum, 36),
        lambda: "xoxb-" + chars(string.digits, 11) + "-" + chars(alnum, 24),
        lambda: "AIza" + chars(alnum + "_-", 35),
        lambda: "sk_live_" + chars(alnum, 24),
        lambda: "glpat-" + chars(alnum, 20),
        lambda: r.choice(names) + r.choice(joins) + chars(hexa, r.choice((16, 18, 20, 32, 40, 64))),
        lambda: r.choice(names) + r.choice(joins) + chars(alnum, r.randint(10, 44)),
        lambda: r.choice(names) + r.choice(joins) + chars(base64, r.randint(20, 64)) + r.choice(("", "=", "==")),
        lambda: chars(alnum, r.randint(32, 64)),
        lambda: r.choice(names) + r.choice(joins) + password(),
        lambda: r.choice(names) + r.choice(joins) + password(),
        lambda: f"-----BEGIN {r.choice(('RSA ', 'EC ', ''))}PRIVATE KEY-----\n" + "\n".join(chars(base64, 64) for _ in range(r.randint(2, 8))) + "\n-----END PRIVATE KEY-----",
    ]
    false = [
        lambda: "".join(r.choice(words) for _ in range(r.randint(6, 12))),
        lambda: "".join(r.choice(words).title() for _ in range(r.randint(4, 8))),
        lambda: "_".join(r.choice(words) for _ in range(r.randint(4, 8))),
        lambda: "".join(r.choice(words) for _ in range(r.randint(6, 12))).upper(),
        lambda: "/".join(r.choice(words) for _ in range(r.randint(5, 9))),
        lambda: chars(string.digits, r.choice((16, 16, 18, 20, 24))),
        lambda: r.choice(("commit ", "sha256:", "md5 ", "checksum: ")) + chars(hexa, r.choice((32, 40, 64))),
        lambda: "-".join(chars(hexa, k) for k in (8, 4, 4, 4, 12)),
        lambda: r.choice(names) + r.choice(joins) + r.choice(("your_api_key_here", "changeme_changeme", "xxxxxxxxxxxxxxxx", "example_secret_value", "placeholder-token")),
        lambda: r.choice(names) + r.choice(joins) + "".join(r.choice(words) for _ in range(r.randint(4, 7))),
        lambda: r.choice("=-_+") * r.randint(16, 60),
        lambda: r.choice(words) * r.randint(6, 14),
        lambda: "".join(r.choice("bcdfghlmnprstvw") + r.choice(("a", "e", "i", "o", "u", "en", "er", "in", "st")) for _ in range(r.randint(6, 14))),
        lambda: "".join(r.choice("BCDFGHLMNPRSTVW") + r.choice(("a", "e", "i", "o", "u", "en", "er")) for _ in range(r.randint(6, 12))).capitalize(),
        lambda: chars(string.ascii_lowercase, r.randint(16, 28)),
        lambda: r.choice(names) + r.choice(joins) + r.choice(long),
        lambda: r.choice(names) + r.choice((": ", ":", "=")) + r.choice(words).title() + r.choice(("-", "_", "/", ".")) + r.choice(long),
        lambda: r.choice(names) + r.choice(joins) + r.choice(("${DB_PASSWORD}", "os.environ.get", "<redacted>", "**********", "undefined", "required", "%(password)s", "https://" + r.choice(words) + ".org/")),
    ]
    rows = []
    for i in range(n):
        label = i % 2
        made = r.choice(real if label else false)()
        path = r.choice(("src/main/app.py", "config/prod.yaml", "src0", "web/page.html", "lib/" + word().replace(" ", "")))
        if not label and r.random() < 0.2:
            path = r.choice(("tests/test_app.py", "doc/example.md", "fixtures/sample.json"))
        rows.append((f"{word(4)} {made}{r.choice(chr(34) + ' .,')} {word(3)}", path, label))
    return rows


@dataclass(frozen=True)
class Model:
    score: str  # SQL of the forest's score over the features' columns
    words: tuple[str, ...]


_trained: dict[tuple, Model] = {}


def train(spark: SparkSession, findings: list[tuple[str, str, int]] | None = None, words: tuple[str, ...] = ()) -> Model:
    """The forest grown on labelled findings, with the corpus's ``words`` beside the fixed ones."""
    words = tuple(dict.fromkeys([*words, *DICTIONARY]))
    rows = findings or labelled_findings(words=words)
    key = (tuple(rows), words)
    if key not in _trained:
        frame = spark.createDataFrame([(i, *row) for i, row in enumerate(rows)], "i int, _t string, _p string, label int").coalesce(1)
        names = list(features(words))
        found = with_features(candidates(frame, ["i", "label"]), words).orderBy("i", "start").select("label", *names).collect()
        x = np.array([list(r)[1:] for r in found], float)
        _trained[key] = Model(forest.sql(forest.grow(x, np.array([r["label"] for r in found])), names), words)
    return _trained[key]


def scan(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", path_col: str = "source", threshold: float = THRESHOLD) -> DataFrame:
    """A row per finding: doc_id, start_at, end_at, kind and score."""
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("_t"), F.coalesce(F.col(path_col).cast("string"), F.lit("")).alias("_p"))
    scored = with_features(candidates(texts, ["doc_id"]), model.words).withColumn("score", F.round(F.expr(model.score), 6))
    kind = F.coalesce(*(F.when(F.col("v").rlike(f"^{p}"), F.lit(n)) for n, p in KINDS.items()), F.when(F.col("f_assigned") == 1, F.lit("assigned")), F.lit("random"))
    return scored.where(F.col("score") >= threshold).select("doc_id", F.col("start").alias("start_at"), (F.col("start") + F.length("v")).alias("end_at"), kind.alias("kind"), "score")


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return scan(docs, train(spark, words=learn_dictionary(docs)))
