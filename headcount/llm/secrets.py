"""Secret scans with DataFrame functions only: three fixed patterns and a randomness test battery.

The fixed patterns give the base spans. The battery looks
at other runs of 20 or more code characters that hold a letter and a digit, infers their encoding (hexadecimal, base 32,
letters and digits of one or both cases, base 64) and runs three tests of the hypothesis that the symbols are drawn at random
from that alphabet:

* chi-squared uniformity: the statistic of the symbol counts against equal use of the alphabet. Runs are short for their
  alphabets, so its mean and spread are taken exactly from the multinomial law, not from the limit law;
* runs above and below the middle of the alphabet;
* serial correlation of neighbours.

The squares of the three normal scores add up to a chi-squared statistic with three degrees of freedom; what it rejects (a
word, a counter, an alphabet) is no secret. What passes may still be text that happens to look even, and the shorter it is the likelier that is: the p value of a candidate is the chance that text, whose symbols repeat
more often, has as small a chi-squared statistic. These p values go through a Benjamini-Hochberg step-up over the document's
candidates with weights in proportion to length, as short runs carry little evidence.

Positions are code points, ends exclusive. They are found without user functions: the pieces between the matches of a
pattern and the matches themselves alternate, so running sums of their lengths are the places. Running values and overlaps go
by blocks of matches, so that a text with many thousands of matches stays cheap.

Defined cases: a null text is empty and has no spans; a text without any trace of the patterns skips the span search; very
long texts are scanned whole; ties of start are ordered by kind; null and repeated ids are rows like others; repeated rows give
repeated results; empty tables and extra columns are fine.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import let

#: The base patterns. A match counts only if the named group or the whole has the least length.
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
#: Tests that a text can pass only if it holds a match of the pattern above with enough characters.
TRACES = {"assign": r"(?i:password|passwd|secret|token|api_?key)[\x22']?\x20*[:=]", "access": "AKIA[A-Z0-9]{16}", "hex": "[0-9a-f]{24}"}
#: The same matches as those of ACCESS and HEX that are long enough: a shorter run cannot hold a longer one.
LONG = {"access": "AKIA[A-Z0-9]{16,}+", "hex": "[0-9a-f]{24,}+"}
KINDS = ("assign", "access", "hex", "random")
RUN = r"[A-Za-z0-9+/_-]{20,}+={0,2}+"
RUN_TRACE = r"(?=[A-Za-z+/_-]*+[0-9])[A-Za-z0-9+/_-]{20}"
FALSE_DISCOVERIES = 0.01
#: 99 % quantile of the chi-squared law with three degrees of freedom: what the squared scores of the three tests add up to at most.
OUTLYING = 11.345
#: Chance that two symbols of a text are equal, about that of English letters.
TEXT_REPEATS = 0.065
#: Alphabets in their usual order.
ALPHABETS = {
    16: "0123456789abcdef",
    32: "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567",
    36: "0123456789abcdefghijklmnopqrstuvwxyz",
    62: "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz",
    64: "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/",
}
MASK = "[secret]"

BLOCK = 64


def _blocks(values: Column, body) -> Column:
    """``body`` of each stretch of BLOCK neighbouring elements."""
    n = F.ceil(F.size(values) / BLOCK).cast("int")
    at = F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda j: body(F.slice(values, j * BLOCK + 1, F.lit(BLOCK))))


def running(values: Column, join, zero: int = 0) -> Column:
    """Running value before each element of an array of ints, for an associative ``join`` (sum, greatest): within blocks, then
    over the blocks. An aggregate that appends to one array copies it at every step; blocks keep those copies short."""
    empty = F.array().cast("array<int>")
    start = F.struct(F.lit(zero).alias("v"), empty.alias("out"))
    step = lambda a, x: F.struct(join(a["v"], x).alias("v"), F.concat(a["out"], F.array(a["v"])).alias("out"))
    inner = _blocks(values, lambda b: F.aggregate(b, start, step))
    before = lambda i: F.aggregate(F.transform(i, lambda x: x["v"]), start, step, lambda a: a["out"])
    return let(inner, lambda i: F.flatten(F.zip_with(i, before(i), lambda x, v: F.transform(x["out"], lambda y: join(v, y)))))


def _places(text: Column, pattern: str, kind: int) -> Column:
    """All matches of the pattern: kind, start, end, match."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))

    def placed(m):
        gaps = F.transform(F.slice(F.split(text, pattern, -1), F.lit(1), F.size(m)), lambda g: F.length(g))
        both = F.zip_with(gaps, m, lambda g, f: F.struct(g.alias("gap"), F.length(f).alias("own"), f.alias("found")))

        def whole(p):
            before = running(F.transform(p, lambda x: x["gap"] + x["own"]), lambda a, x: a + x)

            def one(x, at):
                start = at + x["gap"]
                return F.struct(F.lit(kind).alias("kind"), start.alias("start"), (start + x["own"]).alias("end"), x["found"].alias("found"))

            return F.zip_with(p, before, one)

        return let(both, whole)

    return let(found, placed)


def base_spans(text: Column) -> Column:
    """Array of (kind, start, end, found) of the three base patterns, by start and kind."""
    none = F.array().cast("array<struct<kind:int,start:int,end:int,found:string>>")
    enough = lambda x: F.length(F.regexp_extract(x["found"], ASSIGN, 2)) >= 6
    assign = F.when(text.rlike(TRACES["assign"]), F.filter(_places(text, ASSIGN, 0), enough)).otherwise(none)
    access = F.when(text.rlike(TRACES["access"]), _places(text, LONG["access"], 1)).otherwise(none)
    hexes = F.when(text.rlike(TRACES["hex"]), _places(text, LONG["hex"], 2)).otherwise(none)
    order = lambda a, b: F.when(a["start"] != b["start"], a["start"] - b["start"]).otherwise(a["kind"] - b["kind"])
    return let(F.concat(assign, access, hexes), lambda s: F.when(F.size(s) < 2, s).otherwise(F.array_sort(s, order)))


def _symbols(run: Column) -> Column:
    """struct(k, x): size of the inferred alphabet and the symbols as numbers below it."""
    core = F.regexp_replace(run, "[^A-Za-z0-9]", "")
    k = (
        F.when(run.rlike("[+/]"), 64)
        .when(core.rlike("^([0-9a-f]+|[0-9A-F]+)$"), 16)
        .when(core.rlike("^[A-Z2-7]+$"), 32)
        .when(core.rlike("^([0-9a-z]+|[0-9A-Z]+)$"), 36)
        .otherwise(62)
    )
    text = F.when(k == 64, F.translate(F.regexp_replace(run, "=+$", ""), "-_", "+/")).when(k.isin(16, 36), F.lower(core)).otherwise(core)

    def number(v):
        alphabet = F.element_at(F.create_map(*[F.lit(y) for x in ALPHABETS.items() for y in x]), v["k"])
        one = lambda al: F.transform(F.split(v["t"], ""), lambda c: F.call_function("instr", al, c) - 1)
        return F.struct(v["k"].alias("k"), let(alphabet, one).alias("x"))

    return let(F.struct(k.alias("k"), text.alias("t")), number)


def randomness(run: Column) -> Column:
    """struct(n, k, chi, runs, serial, uneven, p) of one run of code characters: the statistics, the last three of them as normal
    scores under randomness, and p of the hypothesis "text", which is 1 where the tests reject randomness."""

    def scores(v):
        x, k = v["x"], v["k"].cast("double")
        n = F.size(x).cast("double")
        mean = F.aggregate(x, F.lit(0.0), lambda a, c: a + c) / n
        counts = F.transform(F.sequence(F.lit(0), v["k"] - 1), lambda j: F.size(F.filter(x, lambda c: c == j)).cast("double"))
        squares = F.aggregate(counts, F.lit(0.0), lambda a, c: a + c * c)
        at = F.sequence(F.lit(1), F.size(x) - 1)
        flips = F.aggregate(at, F.lit(0.0), lambda a, i: a + ((x[i] < k / 2) != (x[i - 1] < k / 2)).cast("double"))
        spread = F.aggregate(x, F.lit(0.0), lambda a, c: a + (c - mean) * (c - mean))
        together = F.aggregate(at, F.lit(0.0), lambda a, i: a + (x[i] - mean) * (x[i - 1] - mean))
        return F.struct(
            n.alias("n"),
            k.alias("k"),
            (k / n * squares - n).alias("chi"),
            (squares - n).alias("pairs"),
            ((flips - (n - 1) / 2) / F.sqrt((n - 1) / 4)).alias("runs"),
            F.when(spread > 0, together / spread * F.sqrt(n)).otherwise(F.sqrt(n)).alias("serial"),
        )

    def p_text(s):
        # The chi-squared statistic is k / n * (equal pairs + n) - n, so its law is that of the pairs: under uniform use their
        # mean is n (n - 1) / k and their variance 2 n (n - 1) / k (1 - 1 / k).
        even = s["n"] * (s["n"] - 1) / s["k"]
        uneven = (s["pairs"] - even) / F.sqrt(2 * even * (1 - 1 / s["k"]))
        n, repeats = s["n"], F.greatest(F.lit(TEXT_REPEATS), 2 / s["k"])
        expected = n * (n - 1) * repeats
        spread = F.sqrt(2 * expected + 4 * n * (n - 1) * (n - 2) * 0.3 * repeats * repeats)
        z = (s["pairs"] - expected) / spread
        normal = 1 / (1 + F.exp(-(1.5976 * z + 0.07056 * z * z * z)))
        rejected = F.pow(uneven, F.lit(2)) + F.pow(s["runs"], F.lit(2)) + F.pow(s["serial"], F.lit(2)) > OUTLYING
        return F.struct(*(s[c].alias(c) for c in ("n", "k", "chi", "runs", "serial")), uneven.alias("uneven"), F.when(rejected, 1.0).otherwise(normal).alias("p"))

    return let(_symbols(run), lambda v: let(scores(v), p_text))


def _discovered(candidates: Column) -> Column:
    """Step-up over (kind, start, end, found, p, n): those whose weighted p value is at most that of the last success."""

    def judged(c):
        m = F.size(c).cast("double")
        mean = F.aggregate(c, F.lit(0.0), lambda a, x: a + x["n"]) / m
        weighted = F.transform(c, lambda x: x["p"] * mean / x["n"])
        ordered = F.sort_array(weighted)
        hits = F.transform(ordered, lambda p, i: F.when(p <= FALSE_DISCOVERIES * (i + 1) / m, p).otherwise(F.lit(-1.0)))
        limit = F.array_max(hits)
        return let(F.struct(limit.alias("at"), mean.alias("mean")), lambda v: F.filter(c, lambda x: x["p"] * v["mean"] / x["n"] <= v["at"]))

    return F.when(F.size(candidates) == 0, candidates).otherwise(judged(candidates))


def random_spans(text: Column, base: Column) -> Column:
    """Spans (kind, start, end, found) that the battery adds: none overlaps a base span."""
    none = F.array().cast("array<struct<kind:int,start:int,end:int,found:string>>")

    def search(blocks):
        def free(x):
            meets = lambda y: (y["start"] < x["end"]) & (x["start"] < y["end"])
            return x["found"].rlike("[0-9]") & x["found"].rlike("[A-Za-z]") & ~F.exists(blocks, lambda o: meets(o) & F.exists(o["own"], meets))

        def score(x):
            r = lambda s: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"), x["found"].alias("found"), s["p"].alias("p"), s["n"].alias("n"))
            return let(randomness(x["found"]), r)

        found = F.filter(_places(text, RUN, 3), free)
        plain = lambda c: F.transform(c, lambda x: F.struct(*(x[n].alias(n) for n in ("kind", "start", "end", "found"))))
        return let(F.transform(found, score), lambda c: plain(_discovered(c)))

    # base spans by blocks with their extent, so that a run is compared with the blocks and with those that it may meet
    ends = lambda b, end, best: best(F.transform(b, lambda y: y[end]))
    blocks = _blocks(base, lambda b: F.struct(ends(b, "start", F.array_min).alias("start"), ends(b, "end", F.array_max).alias("end"), b.alias("own")))
    return F.when(text.rlike(RUN_TRACE), let(blocks, search)).otherwise(none)


def scan(docs: DataFrame, *keep: str) -> DataFrame:
    """doc_id, kept columns, text, base (array of base spans) and spans (all, by start and kind)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    order = lambda a, b: F.when(a["start"] != b["start"], a["start"] - b["start"]).otherwise(a["kind"] - b["kind"])
    out = docs.select("doc_id", *keep, text.alias("text")).withColumn("base", base_spans(F.col("text")))
    out = out.withColumn("added", random_spans(F.col("text"), F.col("base")))
    both = F.when(F.size("added") == 0, F.col("base")).otherwise(F.array_sort(F.concat("base", "added"), order))
    return out.withColumn("spans", both)


def listed(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    name = lambda x: F.element_at(F.array(*map(F.lit, KINDS)), x["kind"] + 1)
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", name(x), x["start"].cast("string"), x["end"].cast("string"))), ",")


def redacted(text: Column, spans: Column) -> Column:
    """The text with each maximal stretch of spans replaced by a mark."""

    def masked(reach):
        """``reach``: where the spans before each one end, at most."""
        piece = lambda x, at: F.when(x["start"] >= at, F.concat(F.substring(text, at + 1, x["start"] - at), F.lit(MASK))).otherwise("")
        last = F.array_max(F.transform(spans, lambda x: x["end"]))
        return F.concat(F.array_join(F.zip_with(spans, reach, piece), ""), F.substring(text, last + 1, F.length(text)))

    return F.when(F.size(spans) == 0, text).otherwise(let(running(F.transform(spans, lambda x: x["end"]), F.greatest), masked))


def redact_secrets(docs: DataFrame) -> DataFrame:
    """The documents with their secrets masked; n_chars, where there is one, follows the text."""
    packed = docs.select("doc_id", "text", F.struct("*").alias("_row"))
    out = scan(packed, "_row").withColumn("_new", F.when(F.size("spans") > 0, redacted(F.col("text"), F.col("spans"))))
    cols = []
    for c in docs.columns:
        old = F.col("_row")[c]
        new = {"text": F.col("_new"), "n_chars": F.length("_new").cast(dict(docs.dtypes).get("n_chars", "long"))}.get(c)
        cols.append((old if new is None else F.when(F.col("_new").isNotNull(), new).otherwise(old)).alias(c))
    return out.select(*cols)
