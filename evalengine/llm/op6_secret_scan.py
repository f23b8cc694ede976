"""Secret scanning: patterns propose candidates, a random forest removes the false positives.

A candidate is described by its length, its character transitions and spread, the share of it that a word list
covers, the path it stands in and the words beside it. The forest is grown on labelled findings
(``labelled_findings`` writes them in many shapes, with the truth known; a table of own findings may be
given instead) and travels to the executors as arrays of a fixed size.

``scan`` returns a row for each candidate with its score, ``redact`` puts a placeholder in the place of each secret.
Both are one narrow Arrow step over whole texts.

Defined cases: null or empty text has no candidates; overlapping matches are one candidate, their union, with the best score;
positions are in code points; a key's header without an end takes the key's lines after it and no prose; repeated rows
each give their findings; a score of exactly the threshold is a secret; an empty table gives an empty result; extra
columns are ignored by ``scan`` and pass through ``redact``; secrets leave only as a digest.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import math
import random
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evalengine.llm._arrow import appended
from evalengine.llm._common import table
from evalengine.llm._forest import Forest, grow_forest

SCHEMA = "doc_id long, start long, length long, kind string, score double, is_secret boolean, value_sha256 string"
PLACEHOLDER = "[SECRET]"

# Public shapes of keys, words beside secrets and beside look-alikes, and everyday words in identifiers.
PEM = re.compile(r"-----BEGIN [A-Z ]*PRIVATE KEY-----(?:\s*[\w-]{1,40}: [^\n]{0,200}\n)*(?:[\s\\A-Za-z0-9+/=]*+-----END [A-Z ]*PRIVATE KEY-----|(?:(?:\s|\\n)*+[A-Za-z0-9+/=]{24,}+)*+)")
RUN = re.compile(r"eyJ[\w-]{8,}\.[\w-]{8,}\.[\w-]{8,}|[A-Za-z0-9+/_\-]{16,}={0,2}")
NAMED = re.compile(r"(?:password|passwd|pwd|secret|token|api[_-]?key|access[_-]?key)\w*[\"']?\s*(?:=|:|=>)\s*[\"']?([^\s\"'<>]{6,})", re.I)
PREFIXES = {"cloud key": re.compile(r"(?:AKIA|ASIA)[0-9A-Z]{16}$"), "code host token": re.compile(r"gh[pousr]_\w{30,}$|glpat-[\w-]{18,}$"), "chat token": re.compile(r"xox[abprs]-[\w-]{10,}$"), "api key": re.compile(r"(?:sk|pk|rk)[-_](?:live|test|proj)?[-_]?\w{16,}$|AIza[\w-]{30,}$"), "signed token": re.compile(r"eyJ[\w-]+\.")}
NEAR_SECRET = frozenset("token secret password passwd pwd key apikey api auth authorization bearer credential credentials access private login".split())
NEAR_OTHER = frozenset("commit sha sha1 sha256 sha512 md5 hash checksum digest integrity uuid guid build version revision etag id image png jpeg data file path href src url blob tree".split())
PLACEHOLDERS = frozenset("example your xxx xxxx xxxxx changeme placeholder dummy sample test fake here insert todo none null undefined redacted".split())
WORDS = frozenset("the and for with from this that get set user name file path test data value list item node page view model class type index count time date string number object array error message request response server client config default content header footer button image color width height style script table column query result update delete create insert select option input output handler service manager factory builder controller component module package function method return static public private protected interface application example sample your key token secret password access api auth main new old first last next prev start stop end open close read write load save send receive".split())

_WORD = re.compile(r"[A-Za-z]+\d*")


def proposals(text: str) -> list[tuple[int, int, str, list[tuple[int, int]]]]:
    """(start, end, kind, parts) of each candidate, in order and without overlaps: the union of matches that overlap."""
    found = []
    if "-----BEGIN" in text:
        found += [(m.start(), m.end(), "private key") for m in PEM.finditer(text)]
    found += [(m.start(), m.end(), next((k for k, p in PREFIXES.items() if p.match(m[0])), "random text")) for m in RUN.finditer(text)]
    if ("=" in text or ":" in text) and NAMED.search(text):
        found += [(m.start(1), m.end(1), "assigned value") for m in NAMED.finditer(text)]
    out: list[list[tuple[int, int, str]]] = []
    end = 0
    for x in sorted(found):
        if x[0] < end:
            out[-1].append(x)
        else:
            out.append([x])
        end = max(end, x[1])
    known = lambda x: (x[2] in PREFIXES or x[2] == "private key", x[1] - x[0], x[2] != "assigned value")
    return [(g[0][0], max(x[1] for x in g), max(g, key=known)[2], list(dict.fromkeys(x[:2] for x in g))) for g in out]


def candidates(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of each candidate, in order and without overlaps."""
    return [x[:3] for x in proposals(text)]


def describe(text: str, start: int, end: int, source: str | None) -> list[float]:
    value = text[start:end]
    n = len(value)
    kind = [0 if c.isdigit() else 1 if c.islower() else 2 if c.isupper() else 3 for c in value]
    times = Counter(value)
    entropy = -sum(t / n * math.log2(t / n) for t in times.values())
    covered = sum(len(w) for w in re.findall(r"[A-Z]?[a-z]{2,}|[A-Z]{3,}", value) if w.lower() in WORDS)
    smooth = sum(len(w) for w in re.findall(r"(?:[bcdfghjklmnpqrstvwxz]{0,2}[aeiouy]{1,2}){3,}", value.lower()))
    before, after = text[max(0, start - 60) : start], text[end : end + 30]
    words = [w.lower() for w in _WORD.findall(before)]
    last = words[-4:]
    lowered = value.lower()
    return [
        n, sum(a != b for a, b in zip(kind, kind[1:], strict=False)) / max(1, n - 1), entropy, len(times) / n, kind.count(0) / n, kind.count(2) / n, kind.count(3) / n,
        float(all(c in "0123456789abcdefABCDEF" for c in value)), covered / n, smooth / n,
        float(before[-1:] in ("/", "\\", ".", "@", "#")), float(after[:1] in ("/", ".", "@") and after[1:2].isalnum()), float("://" in before.rsplit(" ", 1)[-1]),
        float(any(w in (source or "").lower() for w in ("test", "example", "sample", "mock", "doc"))),
        float(before.rstrip()[-1:] in ("=", ":", "\"", "'")), float(before[-1:] in ("\"", "'")),
        float(sum(w in NEAR_SECRET for w in last)), float(sum(w in NEAR_OTHER for w in last)), float(bool(last) and last[-1] in NEAR_SECRET),
        float(any(w in lowered for w in PLACEHOLDERS)), float(any(p.match(value) for p in PREFIXES.values())), float(value.startswith("-----BEGIN")),
        float(bool(re.fullmatch(r"[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}", value))), max(times.values()) / n,
    ]


def labelled_findings(n: int = 2400, seed: int = 3) -> list[tuple[str, int, int, str, int]]:
    """(text, start, end, source, label) in many shapes: half secrets, half look-alikes."""
    r = random.Random(seed)
    some = lambda chars, k: "".join(r.choice(chars) for _ in range(k))
    hexes, b62 = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    parts = "ka lo mi ter ven sol ar ine pro tu des un el ra gim fo the and ing".split()
    word = lambda: "".join(r.choice(parts) for _ in range(r.randint(1, 3)))
    name = lambda: r.choice(["token", "api_key", "apikey", "secret", "password", "access_key", "auth_token", "SECRET_KEY", "client_secret", "Authorization: Bearer", "key"])
    plain = lambda: r.choice(["commit", "sha256", "checksum", "md5", "hash", "revision", "etag", "id", "digest", "build"])

    def secret() -> tuple[str, str, str]:
        value = r.choice([lambda: some(hexes, r.choice([32, 40, 40, 64])), lambda: some(hexes, 40).upper(), lambda: some(b62, r.randint(20, 44)), lambda: "AKIA" + some(b62[:26] + "0123456789", 16), lambda: "ghp_" + some(b62, 36), lambda: "xoxb-" + some("0123456789", 12) + "-" + some(b62, 24), lambda: "sk-live-" + some(b62, 24), lambda: base64.b64encode(r.randbytes(30)).decode(), lambda: "eyJ" + ".".join(some(b62, 24) for _ in range(3)), lambda: some(b62 + "!@#%&*", r.randint(9, 16)), lambda: "-----BEGIN RSA PRIVATE KEY-----\n" + some(b62, 120) + "\n-----END RSA PRIVATE KEY-----"])()
        key = name()
        if r.random() < 0.2:
            key = key.upper()
        shape = r.choice(['{} = "', "{}: ", "{}='", '"{}": "', "{}=", '{} = "', '{} = "'])
        end = "\"" if shape.endswith("\"") else "'" if shape.endswith("'") else ""
        if value[:4] in ("AKIA", "ghp_", "xoxb", "----") and r.random() < 0.3:
            return "", value, ""
        return shape.format(key), value, end

    def other() -> tuple[str, str, str]:
        return r.choice([
            lambda: (plain() + r.choice([" ", ": ", "=", ' = "']), some(hexes, r.choice([32, 40, 64])), ""),
            lambda: (r.choice(["id ", "uuid=", "", "request "]), "-".join(some(hexes, k) for k in (8, 4, 4, 4, 12)), ""),
            lambda: ("https://" + word() + ".example.com/", "/".join(word() for _ in range(4)) + str(r.randint(1, 9999)), "/x"),
            lambda: ("", "_".join(word() for _ in range(4)) + str(r.randint(0, 99)), "()"),
            lambda: ("", "".join(word().title() for _ in range(4)) + str(r.randint(0, 9)), "("),
            lambda: (name() + ' = "', r.choice(["your_token_here_1234", "xxxxxxxxxxxxxxxxxxxx1", "example_secret_key_123", "changeme123", "${TOKEN_FROM_ENV_1}", "placeholder", "None", "<insert-key-0>"]), '"'),
            lambda: ("", some("0123456789", r.randint(16, 24)), ""),
            lambda: (' integrity="sha384-', some(b62, 64), '"'),
            lambda: ("data:image/png;base64,", base64.b64encode(r.randbytes(60)).decode(), ""),
            lambda: ("", word() + "-" + word() + "-" + word() + "-" + str(r.randint(1990, 2030)), ".html"),
            lambda: (r.choice(["token: ", "password: ", "the key: ", "secret = "]), word() + word(), ""),
            lambda: (r.choice(["/usr/", "src/", "C:/"]), "/".join(word() for _ in range(3)) + "/v" + str(r.randint(10, 99)), ".py"),
            lambda: (word() + ".", str(r.randint(10, 99)) + word() + word() + word(), "@mail.example.com"),
        ])()

    out = []
    for i in range(n):
        head, value, tail = secret() if i % 2 else other()
        before = " ".join(word() for _ in range(r.randint(0, 8)))
        text = f"{before} {head}"
        out.append((f"{text}{value}{tail} {word()} {word()}", len(text), len(text) + len(value), r.choice(["src1", "src7", "web", "repo/tests", "docs"]) if not i % 2 else r.choice(["src1", "src7", "web", "repo"]), i % 2))
    return out


@functools.cache
def grown(n: int = 2400, seed: int = 3) -> Forest:
    found = labelled_findings(n, seed)
    return grow_forest(np.array([describe(t, a, b, s) for t, a, b, s, _ in found]), np.array([y for *_, y in found]))


def findings(texts: list[str], sources: list[str | None], forest: Forest) -> tuple[list[tuple[int, int, int, str]], np.ndarray]:
    """(row, start, end, kind) of every candidate of a batch, and their scores: the best of their parts."""
    at = [(i, *c) for i, t in enumerate(texts) for c in proposals(t)]
    if not at:
        return [], np.zeros(0)
    scores = forest.predict(np.array([describe(texts[i], a, b, sources[i]) for i, *_, parts in at for a, b in parts], np.float64))
    starts = np.cumsum([0, *(len(parts) for *_, parts in at[:-1])])
    return [x[:4] for x in at], np.maximum.reduceat(scores, starts)


def scan(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5) -> DataFrame:
    """A row for each candidate (columns of ``SCHEMA``)."""
    shared = docs.sparkSession.sparkContext.broadcast(forest or grown())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).fill_null("").to_pylist()
            at, scores = findings(texts, batch.column(2).to_pylist(), shared.value)
            if at:
                rows = pa.array([x[0] for x in at])
                yield pa.RecordBatch.from_arrays([batch.column(0).take(rows), pa.array([x[1] for x in at], pa.int64()), pa.array([x[2] - x[1] for x in at], pa.int64()), pa.array([x[3] for x in at]), pa.array(scores), pa.array(scores >= threshold), pa.array([hashlib.sha256(texts[i][a:b].encode()).hexdigest() for i, a, b, _ in at])], names=["doc_id", "start", "length", "kind", "score", "is_secret", "value_sha256"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", "source").mapInArrow(run, SCHEMA)


def redact(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5) -> DataFrame:
    """``docs`` with each secret replaced by a placeholder; ``n_chars`` follows where a text changed."""
    shared = docs.sparkSession.sparkContext.broadcast(forest or grown())
    names = docs.columns

    def columns(batch: pa.RecordBatch) -> list:
        texts = batch.column(names.index("text")).to_pylist()
        at, scores = findings([t or "" for t in texts], batch.column(names.index("source")).to_pylist(), shared.value)
        parts: dict[int, list[str]] = {}
        done: dict[int, int] = {}
        for (i, a, b, _), s in zip(at, scores, strict=True):
            if s >= threshold:
                parts.setdefault(i, []).extend((texts[i][done.get(i, 0) : a], PLACEHOLDER))
                done[i] = b
        for i, found in parts.items():
            texts[i] = "".join((*found, texts[i][done[i] :]))
        return [pa.array(texts, pa.string())]

    new = appended(docs, "clean_text string", columns)
    sized = F.when(F.col("clean_text").eqNullSafe(F.col("text")), F.col("n_chars")).otherwise(F.length("clean_text").cast("long"))
    return new.withColumn("n_chars", sized).withColumn("text", F.col("clean_text")).select(*names)


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
