"""Secret scans: fixed patterns plus a randomness test battery with length-aware false-discovery control (native only).

Spans come from the gaps around the matches: splitting a text by a pattern gives the pieces between matches, and running
sums of code-point lengths give every start and end without a user function.

The battery takes unbroken tokens of 20 or more characters that mix letters and digits, infers their encoding (hex, upper
or lower alphanumeric, base64) and asks four questions whose statistics are near standard normal for uniform random
symbols: chi-squared uniformity over the alphabet, runs above and below the middle, lag-one serial correlation, and the
share of digits.  The squared statistics add up to a chi-squared value of four degrees of freedom with a closed p-value.
Tokens with a large p-value are reported as kind `random`; where the cut lies is decided per encoding and length class, so
that the false ones among the reported stay below a share q.  Random tokens have uniform p-values and others have few above
1/2, so twice the tokens above 1/2 (and one more, for classes with few) estimate how many random ones the class holds; the
reported beyond that number times (1 - cut) count as false.  The lowest cut whose estimated share is at most q is taken, on
a histogram of p-values over all documents, and a floor that is higher for short tokens, where the tests have little power,
holds besides.  Only the histogram (at most 5 encodings x 12 length classes x 64 bins) reaches the driver.

Defined results: a null text is empty (no spans); long texts are scanned whole; an empty table gives no rows; repeated rows
give repeated results; other columns pass through `secret_spans` untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import let, materialize, safe_prefix, table, whole_text

#: The patterns of the base kinds (kind, pattern, group whose length counts, least length).
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
BASE = (
    ("assign", ASSIGN, 2, 8),
    ("access", r"AKIA[A-Z0-9]+", 0, 16),
    ("hex", r"[0-9a-f]{32,}", 0, 32),
)
KINDS = ("assign", "access", "hex", "random")
TOKEN = r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*[0-9])(?=[0-9+/_-]*[A-Za-z])[A-Za-z0-9+/_-]{20,}+"
SPAN = "struct<start:bigint,kind:int,end:bigint>"
#: matches that are folded together
FOLD = 128
MIXED = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz+/"
ALPHABETS = {"hex": "0123456789abcdef", "HEX": "0123456789ABCDEF", "upper": MIXED[:36], "lower": "0123456789abcdefghijklmnopqrstuvwxyz", "base64": MIXED}


def located(text: Column, pattern: str) -> Column:
    """array<struct(m, start, end)> of the leftmost non-overlapping matches, in code points, end exclusive."""
    none = F.array().cast("array<struct<m:string,start:bigint,end:bigint>>")

    def fold(found: Column) -> Column:
        gaps = F.split(text, pattern, -1)

        def with_gaps(g: Column) -> Column:
            start = F.struct(F.lit(0).cast("long").alias("at"), none.alias("out"))

            def step(acc, x):
                s = acc["at"] + F.length(x["g"])
                e = s + F.length(x["m"])
                return F.struct(e.alias("at"), F.concat(acc["out"], F.array(F.struct(x["m"].alias("m"), s.cast("long").alias("start"), e.cast("long").alias("end")))).alias("out"))

            pairs = F.zip_with(found, F.slice(g, 1, F.size(found)), lambda m, gap: F.struct(m.alias("m"), gap.alias("g")))

            def in_runs(all_pairs: Column) -> Column:
                # a fold copies what it has gathered: runs of FOLD matches are folded apart and then moved to their places
                runs = F.transform(F.sequence(F.lit(0), F.floor((F.size(all_pairs) - 1) / FOLD).cast("int")), lambda k: F.aggregate(F.slice(all_pairs, k * FOLD + 1, F.lit(FOLD)), start, step))

                def moved(rs: Column) -> Column:
                    zero = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<bigint>").alias("out"))
                    begins = F.aggregate(rs, zero, lambda acc, r: F.struct((acc["at"] + r["at"]).alias("at"), F.concat(acc["out"], F.array(acc["at"])).alias("out")), lambda acc: acc["out"])
                    return F.flatten(F.zip_with(rs, begins, lambda r, at: F.transform(r["out"], lambda x: F.struct(x["m"].alias("m"), (x["start"] + at).alias("start"), (x["end"] + at).alias("end")))))

                return let(runs, moved)

            return let(pairs, in_runs)

        return let(gaps, with_gaps)

    return F.when(text.rlike(pattern), let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), fold)).otherwise(none)


def base_spans(text: Column, kind: int) -> Column:
    _, pattern, group, least = BASE[kind]
    long_enough = lambda x: F.length(F.regexp_extract(x["m"], pattern, group)) >= least if group else F.length(x["m"]) >= least
    return F.transform(F.filter(located(text, pattern), long_enough), lambda x: F.struct(x["start"].alias("start"), F.lit(kind).alias("kind"), x["end"].alias("end")))


def battery(token: Column) -> Column:
    """struct(encoding, n, p) of a token."""
    plain = F.translate(token, "-_", "")
    folded = F.translate(token, "-_", "+/")
    encoding = F.when(plain.rlike("^[0-9a-f]+$"), "hex").when(plain.rlike("^[0-9A-F]+$"), "HEX").when(plain.rlike("^[0-9A-Z]+$"), "upper").when(plain.rlike("^[0-9a-z]+$"), "lower").otherwise("base64")

    def tests(enc: Column, symbols: Column, alphabet: str) -> Column:
        a = float(len(alphabet))
        codes = F.transform(F.array_remove(F.split(symbols, ""), ""), lambda c: (F.instr(F.lit(alphabet), c) - 1).cast("double"))

        def on(x: Column) -> Column:
            n = F.size(x).cast("double")
            pairs = F.zip_with(F.slice(x, 1, F.size(x) - 1), F.slice(x, 2, F.size(x) - 1), lambda u, v: F.struct(u.alias("u"), v.alias("v")))
            total = lambda arr, f: F.aggregate(arr, F.lit(0.0), lambda s, y: s + f(y))
            squares = total(F.sequence(F.lit(0), F.lit(len(alphabet) - 1)), lambda k: F.pow(F.size(F.filter(x, lambda y: y == k)), F.lit(2.0)))
            chi = (a / n * squares - n - (a - 1)) / F.sqrt(F.lit(2 * (a - 1)) * (n - 1) / n)
            half, mid, var = a / 2, (a - 1) / 2, (a * a - 1) / 12
            runs = (total(pairs, lambda y: ((y["u"] >= half) != (y["v"] >= half)).cast("double")) - (n - 1) / 2) / F.sqrt((n - 1) / 4)
            serial = total(pairs, lambda y: (y["u"] - mid) * (y["v"] - mid)) / var / F.sqrt(n - 1)
            q = 10 / a
            digits = (total(x, lambda y: (y < 10).cast("double")) - n * q) / F.sqrt(n * q * (1 - q))
            stat = let(chi * chi + runs * runs + serial * serial + digits * digits, lambda s: F.exp(-s / 2) * (1 + s / 2))
            return F.struct(enc.alias("encoding"), F.size(x).alias("n"), stat.alias("p"))

        return let(codes, on)

    def by_encoding(e: Column) -> Column:
        out = tests(e, folded, ALPHABETS["base64"])
        for name in ("lower", "upper", "HEX", "hex"):
            out = F.when(e == name, tests(e, plain, ALPHABETS[name])).otherwise(out)
        return out

    return let(encoding, by_encoding)


def length_class(n: Column) -> Column:
    """20-23, 24-31, 32-47, 48-63, 64-95 ...: two classes per doubling, the last one open."""
    return F.least(F.floor(2 * F.log2(F.greatest(n, F.lit(8)).cast("double"))) - 8, F.lit(11)).cast("int")


def p_floor(n: Column) -> Column:
    return F.when(n < 24, F.lit(0.2)).when(n < 32, F.lit(0.1)).otherwise(F.lit(0.02))


def discovery_cut(bins: dict[int, int], q: float) -> float:
    """The lowest cut 2**-e for p-values, given how many lie in each bin (2**-(bin+1), 2**-bin], at which the estimated share of
    tokens reported that are not random is at most q; 1 (nothing is reported) if there is none."""
    half = bins.get(0, 0) + 1
    cut, above = 1.0, 0
    for e in range(1, 65):
        above += bins.get(e - 1, 0)
        random = min(float(above), 2 * half * (1 - 2.0**-e))
        if above and (above - random) <= q * above:
            cut = 2.0**-e
    return cut


def secret_spans(docs: DataFrame, text: str = "text", q: float = 0.05, keep_text: bool = True) -> tuple[DataFrame, str]:
    """docs with <p>base and <p>spans (arrays of start, kind number, end; sorted); returns the frame and the prefix p.

    The scanned rows are written once to the shared folder; keep_text=False leaves the text column out of them.
    """
    p = safe_prefix(docs, "sec")
    t = whole_text(text)
    base = F.array_sort(F.concat(*[base_spans(t, k) for k in range(len(BASE))]))
    found = docs.withColumn(f"{p}base", base).withColumn(f"{p}tok", located(t, TOKEN))
    b = F.col(f"{p}base")
    free = F.filter(F.col(f"{p}tok"), lambda x: (F.length(F.translate(x["m"], "-_", "")) >= 16) & ~F.exists(b, lambda y: (y["start"] < x["end"]) & (x["start"] < y["end"])))
    found = found.withColumn(f"{p}tok", F.transform(free, lambda x: let(battery(x["m"]), lambda r: F.struct(x["start"].alias("start"), x["end"].alias("end"), r["encoding"].alias("encoding"), r["n"].alias("n"), r["p"].alias("p")))))
    found = materialize(found if keep_text else found.drop(text))
    # 64 logarithmic bins of p per encoding and length class
    tests = found.select(F.explode(F.col(f"{p}tok")).alias("x")).select("x.encoding", length_class(F.col("x.n")).alias("cls"), F.least(F.floor(-F.log2(F.greatest(F.col("x.p"), F.lit(1e-19)))), F.lit(63)).cast("int").alias("bin"))
    counts = tests.groupBy("encoding", "cls", "bin").agg(F.count(F.lit(1)).alias("n")).collect()  # at most 5 x 12 x 64 rows
    bins: dict[str, dict[int, int]] = {}
    for r in counts:
        bins.setdefault(f"{r.encoding}:{r.cls}", {})[r.bin] = r.n
    limit = {k: discovery_cut(v, q) for k, v in bins.items()}
    table_of = F.create_map(*[F.lit(v) for kv in limit.items() for v in kv]) if limit else None

    def random_enough(x: Column) -> Column:
        cut = F.coalesce(F.try_element_at(table_of, F.concat_ws(":", x["encoding"], length_class(x["n"]))), F.lit(1.0)) if limit else F.lit(1.0)
        return (x["p"] > cut) & (x["p"] >= p_floor(x["n"]))

    more = F.transform(F.filter(F.col(f"{p}tok"), random_enough), lambda x: F.struct(x["start"].alias("start"), F.lit(3).alias("kind"), x["end"].alias("end")))
    return found.withColumn(f"{p}spans", F.array_sort(F.concat(b, more))).drop(f"{p}tok"), p


def span_list(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"], x["end"])), ",")


def redact(text: Column, spans: Column, mark: str = "[SECRET]") -> Column:
    """text with every span (overlaps merged) replaced by the mark."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out"))

    def step(acc, x):
        fresh = x["start"] >= acc["at"]
        gap = F.when(fresh, F.concat(F.substr(text, acc["at"].cast("int") + 1, (x["start"] - acc["at"]).cast("int")), F.lit(mark))).otherwise(F.lit(""))
        return F.struct(F.greatest(acc["at"], x["end"]).alias("at"), F.concat(acc["out"], gap).alias("out"))

    done = let(F.aggregate(spans, start, step), lambda a: F.concat(a["out"], F.substr(text, a["at"].cast("int") + 1, F.lit(2147483647))))
    return F.when(F.size(spans) == 0, text).otherwise(done)


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    thin, p = secret_spans(docs, keep_text=False)
    base = F.col(f"{p}base")
    count = lambda k: F.size(F.filter(base, lambda x: x["kind"] == k)).cast("long")
    return thin.select("doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"), F.sha2(span_list(base), 256).alias("base_sha256"), span_list(F.col(f"{p}spans")).alias("spans"))
