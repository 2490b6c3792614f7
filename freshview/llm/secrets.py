"""Secret scan: pattern rules plus sliding-window entropy, in DataFrame functions only.

``scan_secrets`` adds to each row an array of spans (code points, end exclusive).
Three pattern rules (``assign``, ``access``, ``hex``) give the base spans. The
fourth kind, ``entropy``, looks at candidate strings and slides a window over
each: the fold's state holds the count of every distinct character in the window and
the sum of ``c * log2(c)`` over them, and both are updated by the one character that
enters and the one that leaves, so no window is counted anew. The threshold depends on the candidate's character class, and an
allow-list takes known harmless strings out: only whole candidates whose segments are
all dictionary-like. The letters and digits beside a separator are a candidate of
their own, by their own class, so a prefix does not raise their threshold. Entropy
spans inside a base span, or inside that of their whole candidate, are left out, since
they add nothing.

Positions without Python: ``split`` by a pattern gives what lies between the
matches, ``regexp_extract_all`` the matches; running sums of both lengths are the
starts. Most rows have no match and pay one ``rlike`` a rule.

Defined cases: a null or empty text has no spans; every input row gives one output
row, also when rows or ids repeat; overlapping spans of different kinds all stay;
input columns other than the id and text are not looked at.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

# Fixed values of the contract, in the order in which kinds are listed.
PATTERNS = {
    "assign": r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""",
    "access": r"AKIA[A-Z0-9]{16,}",
    "hex": r"[0-9a-f]{24,}",
}
ASSIGN_VALUE_CHARS = 6
KINDS = ("assign", "access", "hex", "entropy")

#: A candidate is a run of these characters at least as long as the window.
WINDOW = 20
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
#: Bits a character over the best window that make a candidate a secret, by class.
THRESHOLDS = {"hex": 3.0, "letters_digits": 3.75, "symbols": 3.9}
#: The letters and digits of a candidate between separators, or between one and an end.
PART = r"(?<=[+/_=-])[A-Za-z0-9]{20,}+|(?<![A-Za-z0-9])[A-Za-z0-9]{20,}+(?=[+/_=-])"
#: A word, words in camel case, or a short number; an allowed word or sequence as a whole segment. Repeats
#: of groups are bounded and atomic, as long candidates would else take the matcher's stack or time.
_SEGMENT = r"[A-Z]?[a-z]+(?:[A-Z][a-z]+){0,8}[0-9]{0,2}|[A-Z]+[0-9]{0,2}|[0-9]{1,4}"
_HARMLESS = r"(?i:example|sample|dummy|placeholder|changeme|abcdefghij[k-z]*+|0123456789(?:abcdef)?)"
ALLOW = (
    rf"^(?=(?:.*[-_=+/])?{_HARMLESS}(?:[-_=+/]|$))(?>(?:{_HARMLESS}|{_SEGMENT})(?:[-_=+/]++|$)|[-_=+/]++){{1,60}}$",
    rf"^{_HARMLESS}{{2,20}}$",
    r"^[A-Za-z]+$",
    r"^[0-9]+$",
    rf"^[-_=+/]++(?>(?:{_SEGMENT})(?:[-_=+/]++|$)){{0,60}}$",
)

SPAN = "array<struct<start:int,ord:int,kind:string,end:int>>"


def _spans(text: Column, pattern: str, kind: str, keep=None) -> Column:
    """Spans of the leftmost non-overlapping matches of a pattern; ``keep`` maps to an array of flags."""
    lens = F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda m: F.length(m))
    gaps = F.transform(F.split(text, pattern, -1), lambda p: F.length(p))
    flags = keep(text) if keep else F.transform(lens, lambda _: F.lit(True))
    steps = F.arrays_zip(F.slice(gaps, 1, F.size(lens)).alias("gap"), lens.alias("len"), flags.alias("ok"))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

    def step(state: Column, m: Column) -> Column:
        begin = state["at"] + m["gap"]
        span = F.struct(begin.alias("start"), F.lit(KINDS.index(kind)).alias("ord"), F.lit(kind).alias("kind"), (begin + m["len"]).alias("end"))
        return F.struct(
            (begin + m["len"]).alias("at"),
            F.when(m["ok"], F.concat(state["out"], F.array(span))).otherwise(state["out"]).alias("out"),
        )

    found = F.aggregate(steps, start, step, lambda s: s["out"])
    return F.when(text.rlike(pattern), found).otherwise(F.array().cast(SPAN))


def _bits(count: Column) -> Column:
    """c * log2(c), 0 for an empty count."""
    return F.when(count > 1, count * F.log2(count)).otherwise(F.lit(0.0))


def _let(value: Column, use) -> Column:
    """Bind a value to a lambda variable, so that the lambdas inside do not compute it at each step."""
    return F.element_at(F.transform(F.array(value), use), 1)


def window_entropy(string: Column, window: int = WINDOW) -> Column:
    """Largest Shannon entropy (bits a character) over all windows of a string, by incremental counts.

    Characters are numbered by their first place in the string; the state of the fold
    holds the window's count of each number and the sum over them.
    """
    full = F.log2(F.lit(float(window)))

    def over(codes: Column, distinct: Column) -> Column:
        def step(state: Column, i: Column) -> Column:
            enters, leaves = F.element_at(codes, i), F.when(i > window, F.element_at(codes, F.greatest(i - window, F.lit(1))))
            had, held = F.element_at(state["counts"], enters), F.element_at(state["counts"], leaves)
            # the same character in and out leaves counts and sum as they are
            moves = leaves.isNull() | (leaves != enters)
            gained = F.when(moves, _bits(had + 1) - _bits(had)).otherwise(F.lit(0.0))
            lost = F.when(moves & leaves.isNotNull(), _bits(held) - _bits(held - 1)).otherwise(F.lit(0.0))
            total = state["sum"] + gained - lost
            updated = F.transform(state["counts"], lambda c, k: c + (k + 1 == enters).cast("int") - F.coalesce((k + 1 == leaves).cast("int"), F.lit(0)))
            best = F.when(i >= window, F.greatest(state["best"], full - total / window)).otherwise(state["best"])
            return F.struct(F.when(moves, updated).otherwise(state["counts"]).alias("counts"), total.alias("sum"), best.alias("best"))

        start = F.struct(F.array_repeat(F.lit(0), F.size(distinct)).alias("counts"), F.lit(0.0).alias("sum"), F.lit(0.0).alias("best"))
        return F.aggregate(F.sequence(F.lit(1), F.size(codes)), start, step, lambda s: s["best"])

    def numbered(chars: Column) -> Column:
        return _let(F.array_distinct(chars), lambda d: _let(F.transform(chars, lambda c: F.array_position(d, c).cast("int")), lambda codes: over(codes, d)))

    return F.when(F.length(string) >= window, _let(F.split(string, "(?<=.)(?=.)"), numbered)).otherwise(F.lit(0.0))


def _is_secret(candidate: Column, thresholds: dict[str, float], allow: tuple[str, ...]) -> Column:
    threshold = (
        F.when(candidate.rlike("^[0-9a-fA-F]+$"), F.lit(thresholds["hex"]))
        .when(candidate.rlike("[+/_=-]"), F.lit(thresholds["symbols"]))
        .otherwise(F.lit(thresholds["letters_digits"]))
    )
    allowed = F.lit(False)
    for pattern in allow:
        allowed = allowed | candidate.rlike(pattern)
    return F.when(allowed, F.lit(False)).otherwise(window_entropy(candidate) >= threshold)


def _entropy_spans(text: Column, pattern: str, thresholds: dict[str, float], allow: tuple[str, ...]) -> Column:
    return _spans(text, pattern, "entropy", lambda t: F.transform(F.regexp_extract_all(t, F.lit(pattern), F.lit(0)), lambda c: _is_secret(c, thresholds, allow)))


def _assign_flags(text: Column) -> Column:
    return F.transform(F.regexp_extract_all(text, F.lit(PATTERNS["assign"]), F.lit(2)), lambda v: F.length(v) >= ASSIGN_VALUE_CHARS)


def _plain(spans: Column) -> Column:
    return F.transform(spans, lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end")))


def scan_secrets(df: DataFrame, text: str = "text", out: str = "secret_spans", thresholds: dict[str, float] = THRESHOLDS, allow: tuple[str, ...] = ALLOW) -> DataFrame:
    """All columns of ``df`` plus ``out``: array<struct<kind, start, end>>, by start, then kind as listed."""
    body = F.coalesce(df[text].cast("string"), F.lit(""))
    base = F.array_sort(F.concat(_spans(body, PATTERNS["assign"], "assign", _assign_flags), _spans(body, PATTERNS["access"], "access"), _spans(body, PATTERNS["hex"], "hex")))
    entropy, parts = _entropy_spans(body, CANDIDATE, thresholds, allow), _entropy_spans(body, PART, thresholds, allow)
    found = df.select("*", base.alias("__base_spans"), entropy.alias("__entropy_spans"), parts.alias("__part_spans"))
    b, e, p = F.col("__base_spans"), F.col("__entropy_spans"), F.col("__part_spans")
    outside = lambda x, spans: ~F.exists(spans, lambda y: (y["start"] <= x["start"]) & (x["end"] <= y["end"]))
    fresh = F.concat(F.filter(e, lambda x: outside(x, b)), F.filter(p, lambda x: outside(x, b) & outside(x, e)))
    spans = F.when(F.size(e) + F.size(p) == 0, b).otherwise(F.array_sort(F.concat(b, fresh)))
    return found.select(*[found[c] for c in df.columns], _plain(spans).alias(out))


def redact(df: DataFrame, text: str = "text", spans: str = "secret_spans", mark: str = "[SECRET]") -> DataFrame:
    """Replace each merged run of overlapping spans in the text by a mark; the spans column goes."""
    body = F.col(text)
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(state: Column, s: Column) -> Column:
        gap = F.substring(body, state["at"] + 1, s["start"] - state["at"])
        overlaps = (s["start"] < state["at"]) & (state["at"] > 0)
        return F.struct(
            F.greatest(state["at"], s["end"]).alias("at"),
            F.when(overlaps, state["out"]).otherwise(F.concat(state["out"], gap, F.lit(mark))).alias("out"),
        )

    clean = F.aggregate(F.col(spans), start, step, lambda st: F.concat(st["out"], F.substring(body, st["at"] + 1, F.length(body))))
    changed = F.when(F.size(spans) > 0, clean).otherwise(body)
    return df.withColumn(text, changed).drop(spans)


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def digest(scanned: DataFrame, spans: str = "secret_spans") -> DataFrame:
    """The contract's columns out of scanned rows."""
    s = F.col(spans)
    count = lambda kind: F.size(F.filter(s, lambda x: x["kind"] == kind)).cast("long")
    return scanned.select(
        "doc_id",
        count("assign").alias("n_assign"),
        count("access").alias("n_access"),
        count("hex").alias("n_hex"),
        count("entropy").alias("n_entropy"),
        F.sha2(_joined(F.filter(s, lambda x: x["kind"] != "entropy")), 256).alias("base_sha256"),
        _joined(s).alias("spans"),
    )


def op4_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return digest(scan_secrets(docs))
