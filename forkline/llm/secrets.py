"""Secret scan: fixed patterns, and a battery of randomness tests over token-like runs.

Patterns (the base) find assignments of secrets, access keys and hex runs. The battery judges
every maximal run of 20 or more characters out of ``A-Za-z0-9+/_-``, and every shorter one of
12 or more that steps at least once between letters and digits or from a small letter to a
capital. For each it infers the encoding, the least alphabet that holds the run, and tests

* uniformity: chi-squared of the characters, which is their coincidence in other words;
* runs: characters above and below the alphabet's middle, and the number of steps;
* serial correlation: of alphabet positions, and of vowels with the letter after.

Each test is read twice. Under the hypothesis of a fair random string over the encoding, each
gives a p-value (Wald-Wolfowitz for runs); a run that one of them rejects at a third of
``reject`` is no secret. Under the hypothesis of written language, names included, each gives
the probability to look at least as random: coincidence by its normal limit around that of
fixed letter frequencies, steps by a binomial law (given one step for runs under 20, as only
those are judged), vowels by the normal limit of their correlation. Fisher's method makes one
p-value of the three. So a short word can't be told from a short random string, and isn't.

False-discovery control spans all documents: a first pass writes each run with its p-value,
weights follow the log length and average one (long runs carry more evidence), and the
Benjamini-Hochberg threshold at ``rate`` comes from counts by size of the weighted p-value,
of which a bounded number reaches the driver. Runs that lie inside base spans are a family
of their own: they add no span, but count as ``n_confirmed``.

Null text is empty. Rows of equal or null ids are judged apart; an empty table stays empty.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from forkline.llm.common import id_and_text, lean, through_disk
from forkline.llm.textblock import TextBlock, blocks

# The patterns of the base, their names in order, and the least lengths.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
KINDS = ("assign", "access", "hex", "random")
LEAST_VALUE, LEAST_ACCESS, LEAST_HEX, LEAST_RUN, LEAST_STEPPED = 12, 18, 16, 20, 12
_WORDS = ("password", "passwd", "secret", "token", "api")

_HEX = np.zeros(256, bool)
_HEX[[*range(48, 58), *range(97, 103)]] = True
_RUN = np.zeros(256, bool)
_RUN[[*range(48, 58), *range(65, 91), *range(97, 123), 43, 45, 47, 95]] = True
_DIGIT, _SMALL, _CAPITAL = (np.isin(np.arange(256), r) for r in (range(48, 58), range(97, 123), range(65, 91)))

# Fixed values of written language: how often letters, digits and separators occur (per ten
# thousand of each kind), the share of each kind, the probability of a step, and the
# correlation of vowels with the letter after.
LETTERS = dict(zip("abcdefghijklmnopqrstuvwxyz", (817, 149, 278, 425, 1270, 223, 202, 609, 697, 15, 77, 403, 241, 675, 751, 193, 10, 599, 633, 906, 276, 98, 236, 15, 197, 7), strict=True))
DIGITS = dict(zip("0123456789", (2500, 1800, 1100, 900, 750, 800, 600, 550, 500, 500), strict=True))
SEPARATORS = {"-": 3300, "_": 3300, "/": 3300, "+": 100}
SHARES = ((LETTERS, 0.82), (DIGITS, 0.1), (SEPARATORS, 0.08))
STEP, VOWEL_CORRELATION, VOWELS = 0.12, -0.1, frozenset("aeiouy")
ALPHABETS = (
    ("decimal", "0123456789"),
    ("hex", "0123456789abcdef"),
    ("HEX", "0123456789ABCDEF"),
    ("lower", "abcdefghijklmnopqrstuvwxyz"),
    ("upper", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    ("base32", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    ("lower32", "abcdefghijklmnopqrstuvwxyz234567"),
    ("lower36", "abcdefghijklmnopqrstuvwxyz0123456789"),
    ("upper36", "ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"),
    ("letters", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"),
    ("base62", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"),
    ("base64", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"),
    ("base64url", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-_"),
    ("mixed", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/-_"),
)

def normal_tail(z: float) -> float:
    return 0.5 * math.erfc(z / math.sqrt(2))


def chi_squared_tail(x: float, freedom: int) -> float:
    """Upper tail by the cube-root approximation to the normal."""
    c = 2 / (9 * freedom)
    return normal_tail(((max(x, 0) / freedom) ** (1 / 3) - (1 - c)) / math.sqrt(c))


def alphabet_of(run: str) -> tuple[str, str]:
    own = set(run)
    return next((name, letters) for name, letters in ALPHABETS if own <= set(letters))


def _language(letters: str) -> tuple[float, float]:
    """Sums of squares and cubes of the frequencies of written language over an alphabet, capitals taken as small letters."""
    share = {c: w * n / 10_000 for kind, w in SHARES for c, n in kind.items() if c in set(letters.lower())}
    p = np.array(list(share.values())) / sum(share.values())
    return float((p**2).sum()), float((p**3).sum())


_LANGUAGE = {name: _language(letters) for name, letters in ALPHABETS}


def steps_of(run: str) -> int:
    """Changes between letter and digit, and from a small letter to a capital."""
    return sum(1 for a, b in zip(run, run[1:], strict=False) if (a.isalnum() and b.isalnum() and a.isdigit() != b.isdigit()) or (a.islower() and b.isupper()))


def binomial_tail(least: int, n: int, p: float) -> float:
    """Probability of ``least`` or more hits in ``n`` trials."""
    if least <= 0:
        return 1.0
    term = math.exp(math.lgamma(n + 1) - math.lgamma(least + 1) - math.lgamma(n - least + 1) + least * math.log(p) + (n - least) * math.log1p(-p))
    total = term
    for k in range(least, n):
        term *= (n - k) / (k + 1) * p / (1 - p)
        total += term
    return min(1.0, total)


def fair(run: str) -> dict[str, float]:
    """p-values of a run under fair randomness over its alphabet."""
    _, letters = alphabet_of(run)
    at = {c: i for i, c in enumerate(letters)}
    x = np.array([at[c] for c in run], dtype=float)
    n, k = len(x), len(letters)
    counts = np.bincount(x.astype(int), minlength=k)
    uniform = chi_squared_tail(float(((counts - n / k) ** 2).sum() * k / n), k - 1)
    high = x >= k / 2
    n1, n0 = int(high.sum()), int((~high).sum())
    turns = 1 + int((high[1:] != high[:-1]).sum())
    if n1 and n0:
        mean = 1 + 2 * n1 * n0 / n
        var = max(1e-9, (mean - 1) * (mean - 2) / (n - 1))
        runs = 2 * normal_tail(abs(turns - mean) / math.sqrt(var))
    else:
        runs = 2.0 ** (1 - n)
    centred = x - x.mean()
    power = float((centred**2).sum())
    serial = 2 * normal_tail(abs(float((centred[1:] * centred[:-1]).sum()) / power * math.sqrt(n) + 1 / math.sqrt(n))) if power else 0.0
    return {"uniform": uniform, "runs": runs, "serial": serial}


def language(run: str) -> dict[str, float]:
    """p-values of a run under written language: the probability to look at least as random."""
    n, (c2, c3) = len(run), _LANGUAGE[alphabet_of(run)[0]]
    folded = run.lower()
    counts = np.bincount(np.frombuffer(folded.encode(), np.uint8), minlength=128).astype(float)
    mean = n * (n - 1) * c2
    var = 4 * n * (n - 1) * (n - 2) * (c3 - c2 * c2) + 2 * n * (n - 1) * (c2 - c2 * c2)
    uniform = normal_tail((mean - float((counts * (counts - 1)).sum())) / math.sqrt(var))
    steps = steps_of(run)
    runs = binomial_tail(steps, n - 1, STEP)
    if n < LEAST_RUN:
        runs = min(1.0, runs / binomial_tail(1, n - 1, STEP))
    vowel = np.array([c in VOWELS for c in folded], float)
    centred = vowel - vowel.mean()
    power = float((centred**2).sum())
    serial = normal_tail((float((centred[1:] * centred[:-1]).sum()) / power - VOWEL_CORRELATION) * math.sqrt(n)) if power else 1.0
    return {"uniform": uniform, "runs": runs, "serial": serial}


def fisher(p: list[float]) -> float:
    """One p-value of several independent ones: upper tail of chi-squared with two degrees of freedom for each."""
    half = -sum(math.log(max(x, 1e-300)) for x in p)
    term = total = 1.0
    for k in range(1, len(p)):
        term *= half / k
        total += term
    return min(1.0, math.exp(-half) * total)


def judged(run: str, reject: float) -> tuple[float, bool]:
    """p-value under written language, and whether the run may be a fair random string."""
    tests = fair(run)
    return fisher(list(language(run).values())), min(tests.values()) >= reject / len(tests)


def _spans(block: TextBlock, inside: np.ndarray, least: int, stepped: int | None = None) -> dict[int, list[tuple[int, int]]]:
    """Byte spans in the block, by text, of runs of at least ``least``, or ``stepped`` if they step."""
    s, e, doc = block.spans(inside[block.data])
    keep = e - s >= least
    if stepped is not None:
        a, b = block.data[:-1], block.data[1:]
        step = ((_DIGIT[a] & (_SMALL[b] | _CAPITAL[b])) | (_DIGIT[b] & (_SMALL[a] | _CAPITAL[a])) | (_SMALL[a] & _CAPITAL[b])).astype(np.int64)
        total = np.concatenate([[0], np.cumsum(step), [0]])
        keep |= (e - s >= stepped) & (total[np.maximum(e - 1, 0)] > total[s])
    out: dict[int, list[tuple[int, int]]] = {}
    for i in np.flatnonzero(keep).tolist():
        out.setdefault(int(doc[i]), []).append((int(s[i]), int(e[i])))
    return out


def base_spans(text: str, hex_runs: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """Spans of the base as (start, kind, end) in code points, in order; ``hex_runs`` are given."""
    found = [(a, 2, b) for a, b in hex_runs]
    low = text.lower()
    if any(w in low for w in _WORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST_VALUE]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST_ACCESS]
    return sorted(found)


def union(spans: list[tuple[int, int, int]]) -> tuple[list[int], list[int]]:
    """Starts and ends of the merged stretches of sorted spans."""
    starts, ends = [], []
    for a, _, b in spans:
        if ends and a <= ends[-1]:
            ends[-1] = max(ends[-1], b)
        else:
            starts.append(a)
            ends.append(b)
    return starts, ends


SPAN = "array<struct<start:int,kind:int,end:int>>"
SCANNED = f"doc_id bigint, base {SPAN}, runs array<struct<start:int,end:int,p:double,fair:boolean,inside:boolean>>"


def scanned(docs: DataFrame, reject: float) -> DataFrame:
    """``(doc_id, base, runs)`` of ``(doc_id, text)``: spans of the base, and each judged run."""
    span = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.int32()), ("end", pa.int32())]))
    run = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("p", pa.float64()), ("fair", pa.bool_()), ("inside", pa.bool_())]))
    schema = pa.schema([("doc_id", pa.int64()), ("base", span), ("runs", run)])

    def task(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for first, block in blocks(batch.column(1)):
                hexes, tokens = _spans(block, _HEX, LEAST_HEX), _spans(block, _RUN, LEAST_RUN, LEAST_STEPPED)
                point = np.concatenate([[0], np.cumsum((block.data & 0xC0) != 0x80)])  # code points before each byte
                bases, runs = [], []
                for i in range(block.n_docs):
                    raw, at = block.text(i), int(point[block.edges[i]])
                    text = raw.decode("utf-8", "replace")
                    spans = base_spans(text, [(int(point[a]) - at, int(point[b]) - at) for a, b in hexes.get(i, [])])
                    own, (starts, ends) = [], union(spans)
                    for a, b in tokens.get(i, []):
                        p, may = judged(block.data[a:b].tobytes().decode("ascii"), reject)
                        a, b = int(point[a]) - at, int(point[b]) - at
                        k = bisect_right(starts, a) - 1
                        own.append({"start": a, "end": b, "p": p, "fair": may, "inside": k >= 0 and ends[k] >= b})
                    bases.append([{"start": a, "kind": k, "end": b} for a, k, b in spans])
                    runs.append(own)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, block.n_docs), pa.array(bases, span), pa.array(runs, run)], schema=schema)

    return docs.mapInArrow(lean(task), SCANNED)


#: Counts of weighted p-values have so many bins for each power of ten, down to 1e-300.
BINS = 50


def _bin(p: Column, length: Column, mean: float) -> Column:
    """Bin of a weighted p-value: its lower edge is ``10 ** (-bin / BINS)`` or less, more for smaller ones."""
    weighted = p * F.lit(mean) / F.log2(length)
    return F.greatest(F.lit(0), F.least(F.lit(300 * BINS), F.floor(-F.log10(F.greatest(weighted, F.lit(1e-300))) * BINS))).cast("int")


def least_bin(counts: dict[int, int], rate: float) -> int:
    """The bin from which on the Benjamini-Hochberg step-up rejects; every value counts as the largest of its bin."""
    total, seen, found = sum(counts.values()), 0, 300 * BINS + 1
    for b in sorted(counts, reverse=True):
        seen += counts[b]
        if 10 ** (-b / BINS) <= rate * seen / total:
            found = b
    return found


def thresholds(runs: DataFrame, rate: float) -> dict[bool, tuple[float, int]]:
    """For each family of ``runs(p, n, inside)`` the mean log length and the least bin that is discovered."""
    means = {r["inside"]: float(r["mean"]) for r in runs.groupBy("inside").agg(F.avg(F.log2("n")).alias("mean")).collect()}
    out = {}
    for family, mean in means.items():
        counts = runs.where(F.col("inside") == family).groupBy(_bin(F.col("p"), F.col("n"), mean).alias("bin")).agg(F.count("*").alias("k")).collect()
        out[family] = mean, least_bin({r["bin"]: r["k"] for r in counts}, rate)
    return out


def _spelt(spans: Column) -> Column:
    kind = F.array(*map(F.lit, KINDS))
    return F.concat_ws(",", F.transform(F.array_sort(spans), lambda x: F.concat_ws(":", F.get(kind, x["kind"]), x["start"].cast("string"), x["end"].cast("string"))))


def scan_secrets(docs: DataFrame, rate: float = 0.01, reject: float = 0.001, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document the counts of each kind and its spans, ``kind:start:end`` by start, in code points, end exclusive."""
    rows = through_disk(scanned(id_and_text(docs, id_col, text_col), reject), "secrets")
    runs = rows.select(F.explode("runs").alias("r")).select("r.p", (F.col("r.end") - F.col("r.start")).alias("n"), "r.inside")
    limits = thresholds(runs, rate)

    def found(family: bool) -> Column:
        if family not in limits:
            return F.filter("runs", lambda r: F.lit(False))
        mean, least = limits[family]
        return F.filter("runs", lambda r: (r["inside"] == family) & r["fair"] & (_bin(r["p"], r["end"] - r["start"], mean) >= least))

    added = F.transform(found(False), lambda r: F.struct(r["start"].alias("start"), F.lit(3).alias("kind"), r["end"].alias("end")))
    told = rows.select("doc_id", "base", added.alias("added"), F.size(found(True)).cast("bigint").alias("n_confirmed"))

    def count(kind: int) -> Column:
        return F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("bigint").alias(f"n_{KINDS[kind]}")

    return told.select("doc_id", *map(count, range(3)), F.size("added").cast("bigint").alias("n_random"), "n_confirmed", _spelt(F.col("base")).alias("base_spans"), _spelt(F.concat("base", "added")).alias("spans"))
