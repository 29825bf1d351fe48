"""Secret scans: fixed patterns, then character Markov models compared by log-likelihood ratio.

First-order character models are trained from labelled samples, one for each alphabet of random
strings and one for each style of ordinary identifiers.  A class is the even mixture of its models,
so a string over letters of one case alone is measured against random letters of that case.  A
maximal run of 16 or more key characters is reported as ``markov`` when the log-likelihood ratio of
the two mixtures passes a bound and no pattern already covers any of it; nothing else decides.  The
bound is set on the third of the samples that trains no model, so that a stated share of ordinary
ones passes; the model keeps both error rates.  Pattern matches always stay.

Long numbers (cards, accounts, times) are labelled as ordinary in the samples given here, so runs of
digits are not reported.  Defined results: null and empty texts have no spans; offsets are code
points, end exclusive; spans that tie in start and kind follow by end; repeated rows each get theirs.
"""

from __future__ import annotations

import hashlib
import random
import re
import string
from collections.abc import Callable
from dataclasses import dataclass
from functools import cache, partial

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from polyedge.llm import common

KINDS = ("assign", "access", "hex", "markov")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
# a run of 24 or more starts where no run character stands before it: same matches, fewer objects
HEX_LONG = re.compile(r"(?<![0-9a-f])[0-9a-f]{24,}")
CANDIDATE = re.compile(r"(?<![A-Za-z0-9+/_=.-])[A-Za-z0-9+/_=.-]{16,}")
ALPHABET = string.ascii_letters + string.digits + "+/_=.-"
INDEX = np.full(128, len(ALPHABET), np.int64)
INDEX[[ord(c) for c in ALPHABET]] = np.arange(len(ALPHABET))

Span = tuple[str, int, int]


def base_spans(text: str) -> list[Span]:
    out: list[Span] = []
    for m in ASSIGN.finditer(text):
        if m.end(2) - m.start(2) >= 6:
            out.append(("assign", m.start(), m.end()))
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [("hex", m.start(), m.end()) for m in HEX_LONG.finditer(text)]
    return out


def encode(s: str) -> np.ndarray:
    return INDEX[np.minimum(np.frombuffer(s.encode("utf-32-le", "surrogatepass"), np.uint32), 127)]


def transitions(samples: list[str]) -> np.ndarray:
    """Counts of the next character (columns) after each one (rows; the last row is the start)."""
    k = len(ALPHABET)
    counts = np.zeros((k + 1, k + 1))
    for s in samples:
        x = encode(s)
        np.add.at(counts, (np.concatenate([[k], x[:-1]]), x), 1)
    return counts


def train(samples: list[str], smooth: float) -> np.ndarray:
    """Transition log-probabilities of one first-order model."""
    counts = transitions(samples) + smooth
    return np.log(counts / counts.sum(1, keepdims=True))


def mixture(log_p: np.ndarray, x: np.ndarray) -> float:
    """Log-likelihood of encoded characters under the even mixture of the models of one class."""
    each = log_p[:, np.concatenate([[len(ALPHABET)], x[:-1]]), x].sum(1)
    top = each.max()
    return float(top + np.log(np.exp(each - top).mean()))


@dataclass
class SecretModel:
    random: np.ndarray  # (models, characters + start, characters) log-probabilities
    ordinary: np.ndarray
    bound: float
    missed: float = 0.0  # share of the held-out random strings below the bound
    wrong: float = 0.0  # share of the held-out ordinary ones that pass it

    def ratio(self, s: str) -> float:
        x = encode(s)
        return mixture(self.random, x) - mixture(self.ordinary, x)

    def is_random(self, s: str) -> bool:
        return self.ratio(s) >= self.bound

    def spans(self, text: str) -> list[Span]:
        """All spans, by start, then by kind as listed, then by end."""
        out = base_spans(text)
        base = sorted((a, b) for _, a, b in out)
        for m in CANDIDATE.finditer(text):
            a, b = m.span()
            while b > a and text[b - 1] in ".-_":
                b -= 1
            while a < b and text[a] in ".-_=/+":
                a += 1
            if b - a >= 16 and not any(p < b and a < q for p, q in base) and self.is_random(text[a:b]):
                out.append(("markov", a, b))
        return sorted(out, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


# fixed values: alphabets of keys
LOWER, UPPER, DIGITS = string.ascii_lowercase, string.ascii_uppercase, string.digits
KEY_ALPHABETS = {
    "hex": DIGITS + "abcdef", "upper hex": DIGITS + "ABCDEF", "base32": UPPER + "234567", "lower": LOWER, "upper": UPPER,
    "lower and digits": LOWER + DIGITS, "upper and digits": UPPER + DIGITS, "letters": LOWER + UPPER, "letters and digits": LOWER + UPPER + DIGITS,
    "base64": LOWER + UPPER + DIGITS + "+/", "url safe": LOWER + UPPER + DIGITS + "_-",
}
# fixed values: parts of identifiers, and common words and endings of four languages
PARTS = "get set read write user name file path list item value key index count total data table row column page view model train test load save open close start stop first last next prev error result input output string number date time hash map tree node edge graph image text word line char byte size length width height color source target server client request response http https www com org net example mail static content type version config default local global public private class method function return import export module package build main index html json xml csv"
WORDS = (
    "the of and to in is that it for was on with as be by this are from or an they at have not but what all were when there can your which their said each about how will other time many then them these some her would make like him into has look two more write see number way could people than first water been call who now find long down day did get come made may part over new sound take only little work know place year live back give most very after thing just name good sentence man think say great where help through much before line right too means old any same tell boy follow came want show also around form three small set put end does another well large must big even such because turn here why ask went men read need land different home us move try kind hand picture again change off play spell air away animal house point page letter mother answer found study still learn should world ing ed er ion tion ly ment ness able "
    "le la les de des du un une et en que qui dans pour par sur avec est sont pas plus ce cette ne se au aux il elle nous vous ont mais comme ou son sa ses leur tout faire temps tres bien entre deux aussi sans sous meme encore monde ville jour homme femme eau ellement ique eur ance ie ier ouvrir quelle porter ementre "
    "der die das und ein eine einer ist nicht mit von zu den dem des sich auf fur im auch als an es war bei aus nach wie hat sie wir ihr kann noch werden haben durch wird uber nur oder aber vor zwischen gegen jahr zeit stadt wasser mann frau kinder schon sehr pferd kopf platz jetzt katze zwei heit keit ung lich schaft isch chen sch ver ber ge zwanzig "
    "el los las una por con para como mas pero sus este esta entre cuando muy sin sobre ser tiene tambien me hasta hay donde quien desde todo nos durante todos uno les ni contra otros ese eso ante ellos esto mi antes algunos que unos yo otro otras otra tanto esa estos mucho nada muchos cual poco ella estar estas algo cion ado ando mente dad ero oso ito"
)


def key_samples(rng: random.Random, each: int) -> dict[str, list[str]]:
    return {kind: ["".join(rng.choices(a, k=rng.randint(16, 64))) for _ in range(each)] for kind, a in KEY_ALPHABETS.items()}


def ordinary_samples(rng: random.Random, each: int) -> dict[str, list[str]]:
    """Identifiers, words, hosts, paths and numbers, of 16 characters on."""
    parts, words = PARTS.split(), WORDS.split()

    def grown(make: Callable[[], str], joint: str) -> str:
        s = make()
        while len(s) < 16:
            s += joint + make()
        return s

    def number() -> str:
        return str(rng.randint(0, 2030)) if rng.random() < 0.3 else ""

    styles: dict[str, Callable[[], str]] = {
        "words": lambda: grown(lambda: rng.choice(words), ""),
        "capital words": lambda: grown(lambda: rng.choice(words), "").upper(),
        "titled words": lambda: grown(lambda: rng.choice(words), "").title(),
        "snake": lambda: grown(lambda: rng.choice(parts), "_") + number(),
        "capital snake": lambda: grown(lambda: rng.choice(parts + words), "_").upper() + number(),
        "camel": lambda: rng.choice(parts) + grown(lambda: rng.choice(parts).title(), "") + number(),
        "kebab": lambda: grown(lambda: rng.choice(parts + words), "-") + number(),
        "dotted": lambda: grown(lambda: rng.choice(parts) + number(), "."),
        "path": lambda: grown(lambda: rng.choice(parts) + number(), "/") + rng.choice(["", ".html", ".json", ".py", ".txt"]),
        "sentence": lambda: grown(lambda: rng.choice(words), rng.choice([".", "...", "--", "/"])),
        "number": lambda: "".join(rng.choices(DIGITS, k=rng.randint(16, 24))),
        "groups of digits": lambda: grown(lambda: "".join(rng.choices(DIGITS, k=rng.choice([2, 3, 4, 4]))), rng.choice([".", "-", "/"])),
        "rule": lambda: rng.choice("=-_.+/" + LOWER + UPPER + DIGITS) * rng.randint(16, 60),
        "series": lambda: (rng.choice([LOWER, UPPER, DIGITS, LOWER[::-1], DIGITS + LOWER, LOWER + UPPER]) * 3)[(k := rng.randint(0, 25)) : k + rng.randint(16, 40)],
    }
    return {kind: [make() for _ in range(each)] for kind, make in styles.items()}


def default_samples(seed: int = 11, each: int = 600) -> tuple[dict[str, list[str]], dict[str, list[str]]]:
    """Labelled samples made by rule: random keys by alphabet, ordinary identifiers by style."""
    rng = random.Random(seed)
    return key_samples(rng, each), ordinary_samples(rng, each)


def fit(random_strings: dict[str, list[str]], identifiers: dict[str, list[str]], pass_ordinary: float = 0.0005, least: float = 3.0) -> SecretModel:
    """Models of every alphabet and style from two thirds of the samples; the bound from the rest.

    The bound lets the share ``pass_ordinary`` of the ordinary samples pass and is ``least`` or more.
    """
    # random letters follow each other evenly: more smoothing; ordinary ones do not
    models = [np.stack([train([s for i, s in enumerate(x) if i % 3], smooth) for x in kinds.values()]) for kinds, smooth in ((random_strings, 1.0), (identifiers, 0.02))]
    held = [[s for x in kinds.values() for s in x[::3]] for kinds in (random_strings, identifiers)]
    model = SecretModel(*models, bound=least)
    keys, names = (np.array([model.ratio(s) for s in x]) for x in held)
    if len(names):
        model.bound = max(least, float(np.quantile(names, 1 - pass_ordinary)))
    model.missed = float((keys < model.bound).mean()) if len(keys) else 0.0
    model.wrong = float((names >= model.bound).mean()) if len(names) else 0.0
    return model


@cache
def default_model() -> SecretModel:
    return fit(*default_samples())


def fit_labelled(samples: DataFrame, text_col: str = "text", kind_col: str = "kind", label_col: str = "is_random", max_rows: int = 20_000) -> SecretModel:
    """Fit on a table of labelled strings, at most ``max_rows`` of them (those whose text hashes lowest)."""
    rows = common.draw(samples.where(F.col(text_col).isNotNull() & F.col(label_col).isNotNull()).select(F.col(text_col).alias("t"), F.coalesce(F.col(kind_col).cast("string"), F.lit("")).alias("k"), F.col(label_col).cast("boolean").alias("y")), "t", max_rows)
    classes: tuple[dict[str, list[str]], dict[str, list[str]]] = ({}, {})
    for t, k, y in rows.collect():
        classes[0 if y else 1].setdefault(k, []).append(t)
    if not all(classes):
        raise ValueError("both random strings and ordinary ones are needed")
    return fit(*classes)


def _columns(texts: list[str], model: SecretModel) -> list[list]:
    found = [model.spans(t) for t in texts]
    kinds = [[s[0] for s in f] for f in found]
    return [
        [k.count("assign") for k in kinds],
        [k.count("access") for k in kinds],
        [k.count("hex") for k in kinds],
        [k.count("markov") for k in kinds],
        [[{"kind": k, "start": a, "end": b} for k, a, b in f] for f in found],
    ]


SPAN_TYPE = T.ArrayType(T.StructType([T.StructField("kind", T.StringType()), T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))


def scan(docs: DataFrame, model: SecretModel, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """Append counts per kind and ``found``, the array of spans in order; every row is returned."""
    fields = [(f"n_{k}", T.LongType()) for k in KINDS] + [("found", SPAN_TYPE)]
    return common.with_text_columns(docs, text_col, partial(_columns, model=model), fields, keep)


def _redacted(texts: list[str], model: SecretModel) -> list[list]:
    out, counts = [], []
    for t in texts:
        spans = model.spans(t)
        counts.append(len(spans))
        if spans:
            parts, at = [], 0
            for kind, a, b in spans:
                if a >= at:
                    parts += [t[at:a], f"[{kind} removed]"]
                at = max(at, b)
            t = "".join(parts) + t[at:]
        out.append(t)
    return [out, counts]


def redact(docs: DataFrame, model: SecretModel, text_col: str = "text") -> DataFrame:
    """Replace every span (overlaps as one) by a mark; appends ``redacted_text`` and ``n_secrets``."""
    return common.with_text_columns(docs, text_col, partial(_redacted, model=model), [("redacted_text", T.StringType()), ("n_secrets", T.LongType())])


def _digest_columns(texts: list[str], model: SecretModel) -> list[list]:
    counts = _columns(texts, model)
    joined = [[f"{s['kind']}:{s['start']}:{s['end']}" for s in f] for f in counts[4]]
    base = [hashlib.sha256(",".join(x for x in j if not x.startswith("markov")).encode()).hexdigest() for j in joined]
    return [*counts[:3], base, [",".join(j) for j in joined], counts[3]]


def digest(docs: DataFrame, model: SecretModel) -> DataFrame:
    """The contract's columns, straight from the spans."""
    fields = [("n_assign", T.LongType()), ("n_access", T.LongType()), ("n_hex", T.LongType()), ("base_sha256", T.StringType()), ("spans", T.StringType()), ("n_markov", T.LongType())]
    return common.with_text_columns(docs, "text", partial(_digest_columns, model=model), fields, keep=["doc_id"])
