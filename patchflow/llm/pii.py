r"""Personal data by weak supervision.

Base spans follow fixed patterns and checks.  Besides, wider patterns give
candidates (secrets after a key word, phone numbers without a country code, and base matches that
failed their check).  Three labelers vote on each candidate: its form (regex), a gazetteer
(key words, top-level domains, issuer digits, ranges of addresses, area codes), and
the words before it (context).  Expectation-maximisation over the counts of vote patterns
estimates prior and reliability of each labeler by kind; its posteriors train the final span
classifier, a logistic regression over votes, kind, length and digit share.  Candidates of the
kinds ``secret`` and ``phone`` that it accepts are added where they overlap no base span.

DataFrame functions only: texts, candidates and scores stay in Spark.  The driver gets
the counts of feature patterns alone, at most 2,160 rows whatever the input, and fits both models on
them.  Offsets are code points.  Patterns are possessive and anchored at the start of
a run, so long runs of digits or letters take linear time and no deep recursion.

Null texts are empty and have no spans.  Repeated rows get equal results.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, keyed_rows, no_null_id, read_table

# fixed values: the kinds of the contract in its order, then the kind that the method adds
KINDS = ("email", "ip", "card", "phone", "secret")
BASE = KINDS[:4]

LOCAL = r"A-Za-z0-9._%+-"
TOKEN = r"A-Za-z0-9+/_-"
#: Same matches as the contract's patterns, in the order of KINDS.  The start is that of a run, or where the match before ended.
PATTERNS = {
    "email": rf"(?:(?<![{LOCAL}])|\G)[{LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
WIDER = {
    "secret": rf"(?<![{TOKEN}])(?=[A-Za-z+/_-]*+[0-9])[{TOKEN}]{{16,}}+",
    "phone": r"(?<![0-9+(-])\(?[2-9][0-9]{2}\)?[\x20.-][0-9]{3}[.-][0-9]{4}(?![0-9])",
}
#: A text without these has no match of the kind.
NEEDS = {"email": "@", "phone": "+"}

SECRET_KEYS = ("password", "passwd", "pwd", "token", "secret", "api_key", "apikey", "access_key", "bearer", "auth")
TOP_LEVEL = ("com", "org", "net", "edu", "gov", "io", "de", "fr", "es", "uk", "eu", "info")
CONTEXT = {
    "email": ("mail", "email", "contact", "write"),
    "ip": ("ip", "host", "server", "address"),
    "card": ("card", "visa", "credit", "payment"),
    "phone": ("call", "tel", "phone", "fax", "mobile"),
}
BEFORE = 32


def _matches(text: Column, pattern: str, guard: Column, origin: str, kind: str) -> Column:
    """Array of (kind, origin, gap, size, match, before): gap counts code points since the match before."""
    gaps, found = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(f"({pattern})"), F.lit(1))
    row = F.zip_with(
        F.slice(gaps, 1, F.greatest(F.size(gaps) - 1, F.lit(0))),
        found,
        lambda g, m: F.struct(
            F.lit(kind).alias("kind"), F.lit(origin).alias("origin"), F.length(g).alias("gap"), F.length(m).alias("size"), m.alias("match"), F.lower(F.right(g, F.lit(BEFORE))).alias("before")
        ),
    )
    return F.when(guard, row)


def candidates(docs: DataFrame) -> DataFrame:
    """One row per match of any pattern: k1, k2, kind, origin (base or wider), start, end, match, before."""
    text = F.col("text").cast("string")
    rows = docs.select(no_null_id().alias("k1"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("k2"), text.alias("text"))
    some = rows.filter(F.contains("text", F.lit("@")) | F.col("text").rlike("[0-9]")).dropDuplicates(["k1", "k2"])
    t, digits = F.col("text"), F.col("text").rlike("[0-9]")
    parts = []
    for origin, patterns in (("base", PATTERNS), ("wider", WIDER)):
        for kind, pattern in patterns.items():
            guard = F.contains(t, F.lit(NEEDS[kind])) if origin == "base" and kind in NEEDS else digits
            found = some.select("k1", "k2", F.posexplode(_matches(t, pattern, guard, origin, kind)).alias("i", "m")).select("k1", "k2", "i", "m.*")
            parts.append(found)
    merged = reduce(DataFrame.unionByName, parts)
    upto = F.sum(F.col("gap") + F.col("size")).over(_window("k1", "k2", "origin", "kind"))
    return merged.withColumn("end", upto.cast("long")).withColumn("start", F.col("end") - F.col("size")).drop("gap", "i")


def _window(*keys: str):
    from pyspark.sql import Window

    return Window.partitionBy(*keys).orderBy("i").rowsBetween(Window.unboundedPreceding, Window.currentRow)


def luhn(digits: Column) -> Column:
    size = F.length(digits)

    def add(acc, i):
        d = F.substr(digits, size - i + 1, F.lit(1)).cast("int")
        twice = 2 * d - F.when(d > 4, 9).otherwise(0)
        return acc + F.when(i % 2 == 0, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), size), F.lit(0), add) % 10 == 0


def passes_check() -> Column:
    """The contract's check of a match of its kind."""
    kind, match = F.col("kind"), F.col("match")
    digits = F.regexp_replace(match, "[^0-9]", "")
    n = F.length(digits)
    small = F.forall(F.split(match, r"\."), lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.coalesce(F.right(p, F.lit(3)).try_cast("int"), F.lit(0)) <= 255))
    return F.when(kind == "email", True).when(kind == "ip", small).when(kind == "card", n.between(16, 19) & F.when(n.between(16, 19), luhn(digits)).otherwise(False)).when(kind == "phone", n.between(8, 15)).otherwise(False)


def _ends_with_word(before: Column, words: tuple[str, ...], rest: str) -> Column:
    return before.rlike(rf"(?:^|[^a-z0-9])(?:{'|'.join(words)}){rest}$")


def with_votes(found: DataFrame) -> DataFrame:
    """Adds ``valid`` and the labelers' votes, each -1, 0 or 1, and bucketed features."""
    kind, match, before = F.col("kind"), F.col("match"), F.col("before")
    digits = F.regexp_replace(match, "[^0-9]", "")
    n_digits = F.length(digits)

    def yes_no(c: Column) -> Column:
        return F.when(c, 1).otherwise(-1)

    checked = found.withColumn("valid", F.when(F.col("origin") == "base", passes_check()).otherwise(F.lit(False)))
    form = (
        F.when(F.col("origin") == "base", yes_no(F.col("valid")))
        .when(kind == "secret", F.when(match.rlike("^(?:[0-9a-f]+|[0-9A-F]+)$") & ~match.rlike("^[0-9]+$"), 1).when(n_digits >= 4, 0).otherwise(-1))
        .otherwise(F.when(match.startswith("("), 1).otherwise(0))
    )
    gazetteer = (
        F.when(kind == "email", yes_no(F.lower(F.regexp_extract(match, r"([A-Za-z0-9-]+)$", 1)).isin(*TOP_LEVEL)))
        .when(kind == "ip", F.when(match.rlike(r"^(?:0|22[4-9]|2[34][0-9]|25[0-9])\."), -1).otherwise(1))
        .when(kind == "card", yes_no(match.rlike("^[3-6]")))
        .when((kind == "phone") & (F.col("origin") == "base"), F.when(match.startswith("+0"), -1).otherwise(1))
        .when(kind == "phone", F.when(digits.rlike("^[2-9][0-8][0-9]"), 1).otherwise(-1))
        .otherwise(yes_no(_ends_with_word(before, SECRET_KEYS, r"[\x20\t\x22'=:]{1,6}")))
    )
    context = F.when(kind == "secret", yes_no(before.rlike(r"[=:][\x20\t]?[\x22']?$")))
    for k, words in CONTEXT.items():
        context = context.when(kind == k, F.when(before.rlike(rf"(?:^|[^a-z])(?:{'|'.join(words)})[^a-z]"), 1).otherwise(0))
    share = n_digits / F.col("size")
    return checked.withColumns(
        {
            "form": form,
            "gazetteer": gazetteer,
            "context": context,
            "size_bucket": F.when(F.col("size") < 12, 0).when(F.col("size") < 18, 1).when(F.col("size") < 30, 2).otherwise(3),
            "digit_bucket": F.when(share < 0.25, 0).when(share < 0.6, 1).when(share < 1, 2).otherwise(3),
        }
    )


LABELERS = ("form", "gazetteer", "context")
FEATURES = ("kind", *LABELERS, "size_bucket", "digit_bucket")


def em_posteriors(counts: list[tuple[tuple, int]], rounds: int = 40) -> list[float]:
    """Probability that a span of each pattern (features in the order of FEATURES, number) is right.

    Prior by kind; for each kind, labeler and class a distribution of votes, smoothed by one.
    """
    post = [0.5 + 0.4 * sum(f[1:4]) / 3 for f, _ in counts]
    kinds = sorted({f[0] for f, _ in counts})
    for _ in range(rounds):
        prior, votes = {}, {}
        for k in kinds:
            mine = [(f, n, p) for (f, n), p in zip(counts, post) if f[0] == k]
            total = sum(n for _, n, _ in mine)
            prior[k] = (sum(n * p for _, n, p in mine) + 1) / (total + 2)
            for j in range(3):
                for y in (0, 1):
                    mass = {v: 1.0 + (2.0 if (v == 1) == (y == 1) and v else 0.0) for v in (-1, 0, 1)}  # votes lean to their class
                    for f, n, p in mine:
                        mass[f[1 + j]] += n * (p if y else 1 - p)
                    whole = sum(mass.values())
                    for v, m in mass.items():
                        votes[k, j, y, v] = m / whole
        post = []
        for f, _ in counts:
            odds = math.log(prior[f[0]] / (1 - prior[f[0]])) + sum(math.log(votes[f[0], j, 1, f[1 + j]] / votes[f[0], j, 0, f[1 + j]]) for j in range(3))
            post.append(1 / (1 + math.exp(-max(-30.0, min(30.0, odds)))))
    return post


def fit_classifier(counts: list[tuple[tuple, int]], post: list[float], rounds: int = 200) -> dict[str, float]:
    """Weights of a logistic regression on one-hot features, fitted to the posteriors."""
    weights: dict[str, float] = {"bias": 0.0}
    rows = []
    total = sum(n for _, n in counts) or 1
    for (f, n), p in zip(counts, post):
        active = ["bias", *(f"{name}={v}" for name, v in zip(FEATURES, f)), *(f"{f[0]}:{name}={v}" for name, v in zip(LABELERS, f[1:4]))]
        rows.append((active, n / total, p))
        weights.update({a: 0.0 for a in active if a not in weights})
    squares = {a: 1e-8 for a in weights}
    for _ in range(rounds):
        slope = {a: 1e-5 * w for a, w in weights.items()}
        for active, n, p in rows:
            error = n * (1 / (1 + math.exp(-max(-30.0, min(30.0, sum(weights[a] for a in active))))) - p)
            for a in active:
                slope[a] += error
        for a, s in slope.items():
            squares[a] += s * s
            weights[a] -= 0.5 * s / math.sqrt(squares[a])
    return weights


def _score(weights: dict[str, float]) -> Column:
    if len(weights) == 1:
        return F.lit(0.0)
    table = F.create_map(*[F.lit(x) for kv in weights.items() for x in kv])
    names = [F.lit("bias"), *[F.concat(F.lit(f"{f}="), F.col(f).cast("string")) for f in FEATURES], *[F.concat("kind", F.lit(f":{f}="), F.col(f).cast("string")) for f in LABELERS]]
    total = reduce(lambda a, b: a + b, [F.coalesce(F.element_at(table, n), F.lit(0.0)) for n in names])
    return 1 / (1 + F.exp(-total))


def spans(docs: DataFrame) -> DataFrame:
    """(k1, k2, kind_no, kind, start, end, base) of all spans found, per distinct id and text."""
    from pyspark.sql import Window

    scratch = Scratch(docs.sparkSession, "pii")
    found = scratch.save(with_votes(candidates(docs)).drop("before"))
    counts = [(tuple(r)[:-1], r["count"]) for r in found.groupBy(*FEATURES).count().orderBy(*FEATURES).collect()]  # 5 * 27 * 4 * 4 rows at most
    weights = fit_classifier(counts, em_posteriors(counts))
    base = F.col("valid")
    accepted = found.withColumn("base", base).filter(base | ((F.col("origin") == "wider") & (_score(weights) >= 0.5)))
    by_text = Window.partitionBy("k1", "k2").orderBy("start", F.desc("end"))
    before, after = by_text.rowsBetween(Window.unboundedPreceding, -1), by_text.rowsBetween(1, Window.unboundedFollowing)
    reach, following = F.max(F.when(base, F.col("end"))).over(before), F.min(F.when(base, F.col("start"))).over(after)
    free = (F.coalesce(reach, F.lit(0)) <= F.col("start")) & (F.coalesce(following, F.col("end")) >= F.col("end"))
    kind_no = F.array_position(F.array(*[F.lit(k) for k in KINDS]), F.col("kind"))
    return accepted.withColumn("free", free).filter(F.col("base") | F.col("free")).select("k1", "k2", kind_no.cast("int").alias("kind_no"), "kind", "start", "end", "base")


def find_personal_data(docs: DataFrame) -> DataFrame:
    """doc_id and ``spans``, an array of (kind_no, start, end, kind, base) in order."""
    found = spans(docs).groupBy(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).agg(F.array_sort(F.collect_list(F.struct("kind_no", "start", "end", "kind", "base"))).alias("spans"))
    none = F.array().cast("array<struct<kind_no:int,start:bigint,end:bigint,kind:string,base:boolean>>")
    rows = keyed_rows(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")).select(F.col("_row.doc_id").alias("doc_id"), "_k1", "_k2")
    return rows.join(found.hint("merge"), ["_k1", "_k2"], "left").select("doc_id", F.coalesce("spans", none).alias("spans"))


def mask_personal_data(docs: DataFrame) -> DataFrame:
    """The rows with each span replaced by its kind in brackets; n_chars (where present) anew."""
    found = spans(docs).groupBy(F.col("k1").alias("_k1"), F.col("k2").alias("_k2")).agg(F.array_sort(F.collect_list(F.struct("start", "end", "kind"))).alias("_spans"))
    text = F.col("_row.text").cast("string")
    zero = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("parts"))

    def add(acc, x):
        before = F.substr(text, acc["at"] + 1, F.greatest(x["start"] - acc["at"], F.lit(0)))
        new = F.struct(x["end"].alias("at"), F.concat(acc["parts"], F.array(before, F.concat(F.lit("["), F.upper(x["kind"]), F.lit("]")))).alias("parts"))
        return F.when(x["start"] >= acc["at"], new).otherwise(F.struct(F.greatest(acc["at"], x["end"]).alias("at"), acc["parts"].alias("parts")))

    masked = F.aggregate("_spans", zero, add, lambda acc: F.concat(F.array_join(acc["parts"], ""), F.substr(text, acc["at"] + 1)))
    whole = F.col("_spans").isNull()
    out = keyed_rows(docs).join(found.hint("shuffle_hash"), ["_k1", "_k2"], "left").withColumn("_new", F.when(whole, text).otherwise(masked))
    row = F.col("_row").withField("text", F.col("_new"))
    if "n_chars" in docs.columns:
        row = row.withField("n_chars", F.when(whole, F.col("_row.n_chars")).otherwise(F.length("_new").cast(docs.schema["n_chars"].dataType)))
    return out.select(row.alias("_row")).select("_row.*")


def _base_of(kind: str):
    return lambda x: x["base"] & (x["kind"] == kind)


def op5_personal_data(spark, sf_dir: str) -> DataFrame:
    found = find_personal_data(read_table(spark, sf_dir, "documents"))
    base = F.filter("spans", lambda x: x["base"])
    written = {n: F.array_join(F.transform(a, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",") for n, a in (("base", base), ("all", F.col("spans")))}
    numbers = [F.size(F.filter("spans", _base_of(k))).cast("long").alias(f"n_{k}") for k in BASE]
    return found.select("doc_id", *numbers, F.sha2(written["base"], 256).alias("base_sha256"), written["all"].alias("spans"))
