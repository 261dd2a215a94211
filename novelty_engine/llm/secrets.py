"""Secret scans: fixed patterns plus character Markov models, in DataFrame expressions only.

Base spans are the leftmost non-overlapping matches of three patterns, kept when long enough.  To
them are added candidates: runs of 12 or more letters, digits and `+/_=-`, or the parts of such runs that
no pattern matches, that two first-order Markov models of characters tell apart, one of random
strings, one of ordinary identifiers and words.  A candidate is a secret when its log-likelihood ratio
exceeds `least` in all (odds of e**12) and `margin` per character.

Both models are trained from labelled samples, by default `labelled_samples()`: a few thousand short
strings made by rule from a fixed seed (random strings over hexadecimal, base-64, alphanumeric and
letter alphabets; identifiers, words, numbers and dates in common styles).  A table of 66 x 66 log ratios
is all that reaches the scan.  Null and empty texts have no span.  Offsets are code points, ends exclusive.

Work is linear in the length of a text: positions of n matches come from sums over blocks of 64, never from
arrays that grow a match at a time, and a candidate is read as a list of characters.
"""

from __future__ import annotations

import random
from collections.abc import Callable
from math import log

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: The base patterns, the group whose length decides, and the least length.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
KINDS = ("assign", "access", "hex", "markov")
#: Same spans as the failing-and-dropping scan: runs of one class are maximal, so a short one holds no long one.
ACCESS_LONG, HEX_LONG = r"AKIA[A-Z0-9]{14,}", r"[0-9a-f]{16,}"
_BASE = rf"""(?:(?i:(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+)|{ACCESS_LONG}|{HEX_LONG})"""
_RUN = "[A-Za-z0-9+/_=-]"
#: A run; and, for texts with a base match, such a match or a run from its start (or the end of the match before) to the next one.
CANDIDATE = rf"(?<!{_RUN}){_RUN}{{12,}}+"
PART = rf"{_BASE}|(?:(?<!{_RUN})|\G)(?:(?!{_BASE}){_RUN}){{12,}}+"
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_-="
MARGIN, LEAST = 0.6, 12.0
_WORDS = """account action active address admin agent array async author batch binary block branch buffer build button cache call category channel
check class client cluster column comment commit config connection content control cookie count create current customer data date default delete
device document domain download driver edit element email engine error event export factory feature field file filter folder format frame
function global group handler header history image import index instance label language layer length library line link list login manager
arbeit bericht beispiel dienst ergebnis fehler gesellschaft haus jahr leben mensch nachricht ordnung rechnung schule sprache stadt verbindung
verwaltung wasser wirtschaft wissenschaft zeichen zeitung adresse affaire bureau chemin compte connaissance entreprise environnement exemple
fichier gouvernement histoire maison message monde nouvelle recherche semaine service travail utilisateur valeur voiture archivo ayuda cambio
ciudad conocimiento correo cuenta desarrollo empresa estudio gobierno informacion investigacion mundo nombre palabra pregunta problema pueblo
respuesta servicio sistema trabajo""".split()


def labelled_samples(n: int = 3000, seed: int = 5, words: list[str] = _WORDS) -> list[tuple[str, int]]:
    """(string, 1 for random, 0 for ordinary), made by rule."""
    rng = random.Random(seed)
    pools = ("0123456789abcdef", ALPHABET[:62], ALPHABET[:64], ALPHABET[:26] + ALPHABET[52:62], ALPHABET[:52])
    out = []
    for i in range(n):
        out.append(("".join(rng.choice(pools[i % len(pools)]) for _ in range(rng.randrange(12, 48))), 1))
        picked = [rng.choice(words) for _ in range(rng.randrange(2, 6))]
        number = rng.choice((str(rng.randrange(10)), str(rng.randrange(1990, 2030)), str(rng.randrange(10**3)), str(rng.randrange(10**15)), f"{rng.randrange(1990, 2030)}-{rng.randrange(1, 13):02d}-{rng.randrange(1, 29):02d}"))
        joined = "".join(picked)
        styles = ("".join(w.capitalize() for w in picked), picked[0] + "".join(w.capitalize() for w in picked[1:]), "_".join(picked), "-".join(picked), "/".join(picked), joined, joined.upper(), joined.capitalize(), "_".join(picked).upper(), number)
        text = styles[i % len(styles)]
        tail = rng.choice(("", "", number, f"v{rng.randrange(20)}"))
        out.append((text + (rng.choice("_-") if i % len(styles) in (2, 3, 8) and tail else "") + tail, 0))
    return out


def train(samples: list[tuple[str, int]], smoothing: float = 0.5) -> list[float]:
    """Row-major table of log P(next | character) ratios, random over ordinary; index 0 is any other character."""
    k = len(ALPHABET) + 1
    counts = [[smoothing] * (k * k) for _ in range(2)]
    for text, label in samples:
        at = [ALPHABET.find(c) + 1 for c in text]
        for a, b in zip(at, at[1:]):
            counts[label][a * k + b] += 1
    sums = [[sum(c[a * k : a * k + k]) for a in range(k)] for c in counts]
    return [log(counts[1][i] / sums[1][i // k]) - log(counts[0][i] / sums[0][i // k]) for i in range(k * k)]


def _let(value: Column, then: Callable[[Column], Column]) -> Column:
    """`then` of a value that is worked out once."""
    return F.element_at(F.transform(F.array(value), then), 1)


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0), lambda a, x: a + x)


def _before(values: Column, block: int = 64) -> Column:
    """Sum of the values ahead of each place of an array<int>, in blocks."""

    def placed(blocks: Column) -> Column:
        return _let(F.transform(blocks, _sum), lambda sums: _let(F.transform(sums, lambda _, i: _sum(F.slice(sums, 1, i))), lambda starts: F.flatten(F.transform(blocks, lambda x, i: F.transform(x, lambda _, j: F.get(starts, i) + _sum(F.slice(x, 1, j)))))))

    cut = lambda v: F.transform(F.sequence(F.lit(0), F.floor((F.size(v) - 1) / F.lit(block)).cast("int")), lambda i: F.slice(v, i * block + 1, block))
    return _let(values, lambda v: F.when(F.size(v) == 0, F.array().cast("array<int>")).otherwise(_let(cut(v), placed)))


_SPAN = "array<struct<start:int,kind:int,end:int,value:string>>"


def _spans(text: Column, pattern: str, kind: int, keep: Callable[[Column, Column], Column], group: int = 0) -> Column:
    """Spans of the pattern's matches that `keep(match, group)` accepts.

    One search finds the matches.  Where some are kept, the pieces between them are cut out and positions summed from those.
    """
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    if group:
        found = F.zip_with(found, F.regexp_extract_all(text, F.lit(pattern), F.lit(group)), lambda m, g: F.struct(m.alias("match"), g.alias("group")))
    else:
        found = F.transform(found, lambda m: F.struct(m.alias("match"), m.alias("group")))

    def placed(matches: Column) -> Column:
        lengths = F.zip_with(matches, F.slice(F.split(text, pattern, -1), 1, F.size(matches)), lambda m, b: F.struct(F.length(b).alias("gap"), F.length(m["match"]).alias("own")))

        def span(m: Column, begin: Column) -> Column:
            return F.struct(begin.alias("start"), F.lit(kind).alias("kind"), (begin + F.length(m["match"])).alias("end"), m["match"].alias("value"))

        spans = lambda size, at: F.transform(matches, lambda m, i: F.when(keep(m["match"], m["group"]), span(m, F.get(at, i) + F.get(size, i)["gap"])))
        return _let(lengths, lambda size: _let(_before(F.transform(size, lambda x: x["gap"] + x["own"])), lambda at: F.filter(spans(size, at), lambda x: x.isNotNull())))

    return _let(found, lambda matches: F.when(F.exists(matches, lambda m: keep(m["match"], m["group"])), placed(matches)).otherwise(F.array().cast(_SPAN)))


def _words_of(text: Column) -> Column:
    """Whether one of the assignment's words occurs: a quick test before its pattern."""
    return _let(F.lower(text), lambda low: F.exists(F.array(*map(F.lit, ("password", "passwd", "secret", "token", "api_key", "apikey"))), lambda w: F.contains(low, w)))


def _constants(values: list, kind: str) -> Column:
    """An array that the optimizer folds to one literal."""
    return F.split(F.lit(",".join(map(repr, values))), ",").cast(f"array<{kind}>")


def _random(value: Column, weights: list[float], least: float, margin: float) -> Column:
    """Whether a string of the alphabet's characters looks random."""
    k = len(ALPHABET) + 1
    places = _constants([ALPHABET.find(chr(c)) + 1 for c in range(128)], "int")
    table_ = _constants(weights, "double")
    chars = F.filter(F.split(value, ""), lambda c: c != "")
    codes = F.transform(chars, lambda c: F.coalesce(F.get(places, F.ascii(c)), F.lit(0)))
    ratios = lambda at: F.zip_with(F.slice(at, 1, F.size(at) - 1), F.slice(at, 2, F.size(at) - 1), lambda a, b: F.get(table_, a * k + b))
    total = _let(codes, lambda at: F.aggregate(ratios(at), F.lit(0.0), lambda s, x: s + x))
    return _let(total, lambda t: (t > least) & (t > margin * (F.length(value) - 1)))


def scan(df: DataFrame, key: str = "doc_id", text: str = "text", samples: list[tuple[str, int]] | None = None, least: float = LEAST, margin: float = MARGIN, keep: tuple[str, ...] = ()) -> DataFrame:
    """(key, *keep, base, added): arrays of (start, kind, end, value), kind an index into KINDS."""
    weights = train(labelled_samples() if samples is None else samples)
    rows = df.select(*(F.col(c).alias(f"k{i}") for i, c in enumerate((key, *keep))), F.coalesce(F.col(text), F.lit("")).alias("t"))
    none, every = F.array().cast(_SPAN), lambda m, g: F.lit(True)
    said = rows.select("*", F.when(_words_of(F.col("t")), F.col("t").rlike(ASSIGN)).otherwise(False).alias("said"))
    fixed = said.select(
        "*", F.when(F.col("said"), _spans(F.col("t"), ASSIGN, 0, lambda m, g: F.length(g) >= 12, 2)).otherwise(none).alias("s0"),
        F.when(F.contains("t", F.lit("AKIA")), _spans(F.col("t"), ACCESS_LONG, 1, every)).otherwise(none).alias("s1"), _spans(F.col("t"), HEX_LONG, 2, every).alias("s2"),
    )
    random_ = lambda m, g: _random(m, weights, least, margin)
    parts = _spans(F.col("t"), PART, 3, lambda m, g: ~m.rlike(f"^{_BASE}") & random_(m, g))
    added = F.when(F.col("said") | (F.size("s1") + F.size("s2") > 0), parts).otherwise(_spans(F.col("t"), CANDIDATE, 3, random_))
    found = fixed.select("*", F.array_sort(F.concat("s0", "s1", "s2")).alias("base"), added.alias("added"))
    return found.select(*(F.col(f"k{i}").alias(c) for i, c in enumerate((key, *keep))), "base", "added")


def rendered(spans: Column) -> Column:
    kinds = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(kinds, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(df: DataFrame, key: str = "doc_id", text: str = "text", mask: str = "[secret]", keep: tuple[str, ...] = (), **options) -> DataFrame:
    """(key, text, *keep): every found span replaced by `mask`; spans that overlap are replaced together.

    A text is cut into characters once; a character is kept unless a span covers it, which the sums of starts less ends tell.
    """
    spans = scan(df, key, text, keep=(text, *keep), **options)
    rows = spans.select(key, text, *keep, F.concat("base", "added").alias("spans"))
    whole = F.coalesce(F.col(text), F.lit(""))
    ends = F.array_sort(F.flatten(F.transform("spans", lambda s: F.array(F.struct(s["start"].alias("at"), F.lit(1).alias("step")), F.struct(s["end"].alias("at"), F.lit(-1).alias("step"))))))

    def masked(marks: Column) -> Column:
        """Pieces between neighbouring marks, each with the number of spans open there; a piece is text or the end of a mask."""
        opened = _before(F.transform(marks, lambda m: m["step"]))
        pieces = lambda chars, deep: F.transform(marks, lambda m, i: _piece(chars, marks, deep, m, i, mask))
        last = lambda chars: F.array_join(F.slice(chars, F.element_at(marks, -1)["at"] + 1, F.size(chars)), "")
        return _let(F.filter(F.split(whole, ""), lambda c: c != ""), lambda chars: _let(opened, lambda deep: F.concat(F.array_join(pieces(chars, deep), ""), last(chars))))

    return rows.select(key, F.when(F.size("spans") == 0, F.col(text)).otherwise(_let(ends, masked)).alias(text), *keep)


def _piece(chars: Column, marks: Column, deep: Column, mark: Column, i: Column, mask: str) -> Column:
    """What stands between the mark before and this one: text outside spans, nothing inside, the mask where the last span ends."""
    begin = F.coalesce(F.get(marks, i - 1)["at"], F.lit(0))
    outside = F.array_join(F.slice(chars, begin + 1, mark["at"] - begin), "")
    return F.when(F.get(deep, i) == 0, outside).when(F.get(deep, i) + mark["step"] == 0, F.lit(mask)).otherwise("")


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(table(spark, sf_dir, "documents"))
    number = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("bigint")
    return found.select(
        "doc_id", number(0).alias("n_assign"), number(1).alias("n_access"), number(2).alias("n_hex"),
        F.sha2(rendered(F.col("base")), 256).alias("base_sha256"), rendered(F.array_sort(F.concat("base", "added"))).alias("spans"), F.size("added").cast("bigint").alias("n_markov"),
    )
