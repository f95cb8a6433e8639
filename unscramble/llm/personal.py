"""Personal data: high-recall candidates, boosted trees over format and context, calibrated thresholds.

Generators are regular expressions; their matches may overlap. Base generators (email, ip, card, phone) have fixed
rules, and what meets the rules is always a span. All other candidates are scored by boosted trees, which are written
out as SQL expressions; a logistic curve, fitted to examples that the trees have not seen, makes the score a
probability, and a candidate whose probability reaches the threshold of its kind may become a span. Of candidates that
overlap the likeliest stays (then the first, then the longest), and none stays that overlaps a base span.

The main path has only built-in expressions: matches come from regexp_extract_all, their places from the lengths of
what split leaves between them. Trees are fitted on the driver to a fixed number of made-up examples whose features
come from the same expressions. Places count code points, ends are exclusive.

Null text is empty and has no spans. Matches never depend on other rows.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unscramble.llm.common import table

KINDS = ("email", "ip", "card", "phone")
CONTEXT = 40  # code points before a candidate that its features look at

#: name, kind, base, pattern, and a text that every match holds (or none). Runs of digits are taken possessively, so
#: that no pattern backtracks over long runs; each is the same language, leftmost and longest, as its plain form.
GENERATORS = (
    ("email", "email", True, r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@"),
    ("ip", "ip", True, r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", "."),
    ("card", "card", True, r"(?=[0-9](?:[ -]?[0-9]){12})[0-9]++(?:[ -][0-9]++)*+", None),
    ("phone", "phone", True, r"\+[0-9][ ().0-9-]+[0-9]", "+"),
    ("spelled_email", "email", False, r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64} ?[(\[{<]at[)\]}>] ?[A-Za-z0-9-]{1,63}(?: ?(?:\.|[(\[{<]dot[)\]}>]) ?[A-Za-z0-9-]{1,63}){1,8}", "at"),
    ("long_ip", "ip", False, r"(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Za-z:])", ":"),
    ("parted_card", "card", False, r"(?<![0-9])[0-9]{4}([./_])[0-9]{4}\1[0-9]{4}\1[0-9]{4}(?![0-9])", None),
    ("plain_phone", "phone", False, r"(?<![0-9A-Za-z.+/-])\(?[0-9]{3}\)?[ .-]?[0-9]{3}[ .-][0-9]{4}(?![0-9A-Za-z/-])", None),
    ("double_zero_phone", "phone", False, r"(?<![0-9])00[1-9][0-9]{0,2}(?:[ .-]?[0-9]{2,4}){2,4}(?![0-9])", "00"),
)

WANTED = {
    "email": r"(?i)(mail|contact|write|reach|courriel|correo)",
    "ip": r"(?i)(\bip\b|address|host|server|login|adresse)",
    "card": r"(?i)(card|visa|master|credit|debit|karte|carte|tarjeta)",
    "phone": r"(?i)(phone|\btel|call|mobile|\bfax|cell|whatsapp|ruf|llame)",
}
UNWANTED = r"(?i)(order|invoice|isbn|issn|version|serial|part|ref|sku|ticket|build|patent|hash|lot|model|page)"


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    def add(total: Column, i: Column) -> Column:
        d = F.substring(digits, F.length(digits) - i + 1, F.lit(1)).cast("int")
        double = d * 2 - F.when(d > 4, 9).otherwise(0)
        return total + F.when(i % 2 == 0, double).otherwise(d)

    return (F.length(digits) > 0) & (F.aggregate(F.sequence(F.lit(1), F.greatest(F.length(digits), F.lit(1))), F.lit(0), add) % 10 == 0)


def holds(kind: str, m: Column) -> Column:
    """Does a base match meet its kind's rule?"""
    n = F.length(_digits(m))
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: F.length(F.ltrim(p, F.lit("0"))).between(0, 3) & (F.coalesce(F.ltrim(p, F.lit("0")).try_cast("int"), F.when(F.ltrim(p, F.lit("0")) == "", 0).otherwise(999)) <= 255))
    if kind == "card":
        return n.between(13, 19) & _luhn(_digits(m))
    return n.between(9, 15) if kind == "phone" else F.lit(True)


def located(text: Column, pattern: str, needs: str | None) -> Column:
    """Matches as an array of (start, end, m)."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    if needs:
        found = F.when(F.contains(text, F.lit(needs)), found)
    return found


def placed(text: Column, found: Column, pattern: str) -> Column:
    none = F.expr("cast(array() as array<struct<start: int, end: int, m: string>>)")
    between = F.split(text, pattern, -1)

    def add(acc: Column, i: Column) -> Column:
        start = acc["at"] + F.length(F.element_at(acc["gaps"], i))
        m = F.element_at(acc["ms"], i)
        end = start + F.length(m)
        one = F.struct(start.alias("start"), end.alias("end"), m.alias("m"))
        return F.struct(end.alias("at"), acc["gaps"].alias("gaps"), acc["ms"].alias("ms"), F.array_append(acc["out"], one).alias("out"))

    first = F.struct(F.lit(0).alias("at"), between.alias("gaps"), found.alias("ms"), none.alias("out"))
    out = F.aggregate(F.sequence(F.lit(1), F.size(found)), first, add, lambda acc: acc["out"])
    return F.when(F.size(found) > 0, out).otherwise(none)


def features(generator: int, m: Column, before: Column, after: Column) -> list[Column]:
    """Numbers that the trees look at, all as double."""
    _, kind, _, _, _ = GENERATORS[generator]
    flag = lambda c: F.when(c, 1.0).otherwise(0.0)
    digits = _digits(m)
    return [
        F.lit(float(generator)),
        F.length(digits).cast("double"),
        F.length(m).cast("double"),
        F.length(F.regexp_replace(m, "[^ ().:/_-]", "")).cast("double"),
        flag(_luhn(digits)),
        flag(F.rlike(before, F.lit(WANTED[kind]))),
        flag(F.rlike(before, F.lit(UNWANTED))),
        flag(F.rlike(before, F.lit(r"[A-Za-z0-9#$]$"))),
        flag(F.rlike(after, F.lit(r"^[A-Za-z0-9%]"))),
        flag(holds(kind, m)) if GENERATORS[generator][2] else F.lit(0.5),
    ]


# --- boosted trees ----------------------------------------------------------------------------------------------


def made_up_examples(n: int = 120) -> list[tuple[int, str, str, str, int]]:
    """(generator, before, m, after, label), a fixed number for each generator that is not base."""
    g = np.random.Generator(np.random.PCG64(7))
    pick = lambda xs: xs[g.integers(len(xs))]
    digits = lambda k: "".join(map(str, g.integers(0, 10, k)))
    filler = ("", "and then the ", "lorem ipsum dolor, ", "was seen. ", "of which the ")
    bad = ("order no ", "invoice ", "ISBN ", "version ", "serial ", "part ", "ref ", "SKU ", "ticket ", "build ", "lot ")
    good = {"email": ("mail me at ", "contact: ", "write to "), "ip": ("ip ", "host ", "server at "), "card": ("card ", "visa ", "credit card no "), "phone": ("phone ", "call ", "tel. ", "mobile: ", "fax ")}

    def luhn(ok: bool) -> str:
        body = "4" + digits(14)
        total = sum(d if i % 2 else d * 2 - 9 * (d > 4) for i, d in enumerate(map(int, body)))
        return body + str((-total + (0 if ok else int(g.integers(1, 10)))) % 10)

    def render(name: str, label: int) -> str:
        if name == "spelled_email":
            a, b = pick(("[]", "()", "{}"))
            return f"{pick(('jan', 'm.lee', 'info', 'kim_9'))} {a}at{b} {pick(('mail', 'example', 'post'))} {a}dot{b} {pick(('com', 'org', 'net'))}" if label else f"look (at) this. {pick(('now', 'then', 'here'))}"
        if name == "long_ip":
            return ":".join(f"{x:x}" for x in g.integers(4096, 65536, 8)) if label else ":".join(digits(2) for _ in range(8))
        if name == "parted_card":
            x, s = luhn(bool(label)), pick("./_")
            return s.join(x[i : i + 4] for i in range(0, 16, 4))
        if name == "plain_phone":
            return pick(("({}) {}-{}", "{}-{}-{}", "{}.{}.{}", "{} {} {}")).format(digits(3), digits(3), digits(4))
        return "00" + pick(("1", "44", "49", "33")) + "".join(pick((" ", "-")) + digits(3) for _ in range(3))

    out = []
    for at, (name, kind, base, _, _) in enumerate(GENERATORS):
        for k in range(0 if base else n):
            label = k % 2
            clear = kind in ("email", "ip", "card")  # their form tells; a phone needs its context
            lead = pick(good[kind]) if label and (not clear or k % 4 < 3) else pick(bad) if k % 4 == 2 or (not label and k % 4 == 0 and not clear) else ""
            out.append((at, pick(filler) + lead, render(name, label), pick((" ", ", ", ".", "")) if label else pick((" ", "%", ".", "")), label))
    return out


class Trees:
    """Boosted trees of depth two for the logistic loss, fitted with numpy."""

    def __init__(self, x: np.ndarray, y: np.ndarray, rounds: int = 30, rate: float = 0.4):
        self.start = float(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3)))
        self.trees: list[tuple] = []
        score = np.full(len(y), self.start)
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-score))
            tree = self._grow(x, y - p, p * (1 - p), rate, 2)
            self.trees.append(tree)
            score += self._apply(tree, x)

    def _grow(self, x: np.ndarray, g: np.ndarray, h: np.ndarray, rate: float, depth: int) -> tuple:
        leaf = ("leaf", float(rate * g.sum() / (h.sum() + 1.0)))
        if not depth or len(g) < 8:
            return leaf
        best = (1e-6, -1, 0.0)
        gain = lambda m: g[m].sum() ** 2 / (h[m].sum() + 1.0)
        for f in range(x.shape[1]):
            values = np.unique(x[:, f])
            for cut in (values[1:] + values[:-1]) / 2:
                low = x[:, f] < cut
                best = max(best, (gain(low) + gain(~low) - g.sum() ** 2 / (h.sum() + 1.0), f, float(cut)))
        if best[1] < 0:
            return leaf
        low = x[:, best[1]] < best[2]
        return ("split", best[1], best[2], self._grow(x[low], g[low], h[low], rate, depth - 1), self._grow(x[~low], g[~low], h[~low], rate, depth - 1))

    def _apply(self, tree: tuple, x: np.ndarray) -> np.ndarray:
        if tree[0] == "leaf":
            return np.full(len(x), tree[1])
        return np.where(x[:, tree[1]] < tree[2], self._apply(tree[3], x), self._apply(tree[4], x))

    def score(self, x: np.ndarray) -> np.ndarray:
        return self.start + sum(self._apply(t, x) for t in self.trees)

    def column(self, x: Column) -> Column:
        """The score as an expression over an array of features."""

        def of(tree: tuple) -> Column:
            if tree[0] == "leaf":
                return F.lit(tree[1])
            return F.when(x[tree[1]] < tree[2], of(tree[3])).otherwise(of(tree[4]))

        out = F.lit(self.start)
        for t in self.trees:
            out = out + of(t)
        return out


def calibrate(score: np.ndarray, y: np.ndarray, rounds: int = 50) -> tuple[float, float]:
    """a and b so that 1 / (1 + exp(-(a score + b))) is the probability of label 1, by Newton's method.

    Targets are drawn in a little from 0 and 1 by the numbers of examples, so that a clean split keeps finite slopes.
    """
    up, down = y.sum(), (1 - y).sum()
    target = np.where(y > 0, (up + 1) / (up + 2), 1 / (down + 2))
    x = np.stack([score, np.ones_like(score)], 1)
    w = np.zeros(2)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        w += np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 1e-6 * np.eye(2), x.T @ (target - p))
    return float(w[0]), float(w[1])


class Model:
    """Trees, the curve from scores to probabilities, and for each kind the least probability of a span."""

    def __init__(self, trees: Trees, curve: tuple[float, float], limits: dict[str, float]):
        self.trees, self.curve, self.limits = trees, curve, limits

    def probability(self, x: Column) -> Column:
        return 1 / (1 + F.exp(-(self.trees.column(x) * self.curve[0] + self.curve[1])))

    def probabilities(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.trees.score(x) * self.curve[0] + self.curve[1])))


_fitted: list[Model] = []


def fitted(spark: SparkSession) -> Model:
    """The model, fitted once: trees on two thirds of the examples, curve and thresholds on the rest.

    A kind's threshold is the least probability, one half or more, from which on 99 % of the rest are right.
    """
    if not _fitted:
        rows = made_up_examples()
        quote = lambda s: "'" + s.replace("\\", "\\\\").replace("'", "\\'") + "'"
        values = ",".join(f"({k}, {at}, {quote(b)}, {quote(m)}, {quote(a)})" for k, (at, b, m, a, _) in enumerate(rows))
        df = spark.sql(f"SELECT * FROM VALUES {values} AS t(k, generator, lead, m, tail)")
        vector = F.coalesce(*[F.when(F.col("generator") == i, F.array(*features(i, F.col("m"), F.col("lead"), F.col("tail")))) for i, x in enumerate(GENERATORS) if not x[2]])
        x = np.zeros((len(rows), 10))
        for r in df.select("k", vector.alias("x")).collect():
            x[r["k"]] = r["x"]
        y = np.array([r[4] for r in rows], float)
        kind = np.array([GENERATORS[r[0]][1] for r in rows])
        fit = np.arange(len(rows)) % 3 > 0
        trees = Trees(x[fit], y[fit])
        score = trees.score(x)
        a, c = calibrate(score[~fit], y[~fit])
        p = 1 / (1 + np.exp(-(a * score + c)))
        limits = {}
        for k in KINDS:
            mine = ~fit & (kind == k)
            cuts = [c for c in np.unique(p[mine]) if y[mine][p[mine] >= c].mean() >= 0.99]
            limits[k] = max(float(min(cuts, default=np.inf)), 0.5)
        _fitted.append(Model(trees, (a, c), limits))
    return _fitted[0]


# --- over documents ---------------------------------------------------------------------------------------------


def _span(kind_no: int) -> Callable[[Column], Column]:
    return lambda c: F.struct(F.lit(kind_no).alias("kind_no"), c["start"].alias("start"), c["end"].alias("end"))


def _meets(kind: str) -> Callable[[Column], Column]:
    return lambda c: holds(kind, c["m"])


def _scored(generator: int, kind_no: int, whole: Column, model: Model) -> Callable[[Column], Column]:
    def of(c: Column) -> Column:
        before = F.substring(whole, F.greatest(c["start"] - CONTEXT, F.lit(0)) + 1, F.least(c["start"], F.lit(CONTEXT)))
        vector = F.array(*features(generator, c["m"], before, F.substring(whole, c["end"] + 1, F.lit(4))))
        p = F.transform(F.array(vector), model.probability)[0]  # binds the vector once
        return F.struct((-p).alias("cost"), c["start"].alias("start"), (-c["end"]).alias("back"), F.lit(kind_no).alias("kind_no"), c["end"].alias("end"))

    return of


def _chosen(base: Column, scored: Column) -> Column:
    """Spans (kind_no, start, end) of scored candidates in order of likelihood, each if nothing before it overlaps it."""
    none = F.expr("cast(array() as array<struct<kind_no: int, start: int, end: int>>)")

    def meets(s: Column) -> Callable[[Column], Column]:
        return lambda t: (t["start"] < s["end"]) & (s["start"] < t["end"])

    def add(acc: Column, s: Column) -> Column:
        one = F.struct(s["kind_no"].alias("kind_no"), s["start"].alias("start"), s["end"].alias("end"))
        return F.when(F.exists(acc, meets(s)) | F.exists(base, meets(s)), acc).otherwise(F.array_append(acc, one))

    return F.array_sort(F.aggregate(F.array_sort(scored), none, add))


def _of_kind(kind_no: int) -> Callable[[Column], Column]:
    return lambda s: s["kind_no"] == kind_no


def find_spans(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with columns base_spans and added_spans: arrays of (kind_no, start, end) in order. Nothing is shuffled.

    Columns of docs with these two names give way; all others stay as they are, whatever their names.
    """
    spark = docs.sparkSession
    model = fitted(spark)
    own = _Names(docs)
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    step = docs.withColumn(own("whole"), whole)
    whole = F.col(own("whole"))
    step = step.withColumns({own(f"m{i}"): located(whole, g[3], g[4]) for i, g in enumerate(GENERATORS)})
    step = step.withColumns({own(f"p{i}"): placed(whole, F.col(own(f"m{i}")), g[3]) for i, g in enumerate(GENERATORS)})
    base, added = [], []
    for i, (_, kind, is_base, _, _) in enumerate(GENERATORS):
        no = KINDS.index(kind)
        if is_base:
            base.append(F.transform(F.filter(own(f"p{i}"), _meets(kind)), _span(no)))
        else:
            scored = F.transform(own(f"p{i}"), _scored(i, no, whole, model))
            added.append(F.filter(scored, _likely(model.limits[kind])))
    step = step.withColumn(BASE, F.array_sort(F.concat(*base))).withColumn(own("scored"), F.concat(*added))
    step = step.withColumn(ADDED, F.when(F.size(own("scored")) > 0, _chosen(F.col(BASE), F.col(own("scored")))).otherwise(F.filter(BASE, lambda _: F.lit(False))))
    return step.select(*[x for x in docs.columns if x not in (BASE, ADDED)], BASE, ADDED)


BASE, ADDED = "base_spans", "added_spans"


def _likely(limit: float) -> Callable[[Column], Column]:
    return lambda s: -s["cost"] >= limit


class _Names:
    """Names of columns that docs doesn't have."""

    def __init__(self, docs: DataFrame):
        self.lead = "_"
        while any(c.lower().startswith(f"{self.lead}pii_") for c in docs.columns):
            self.lead += "_"

    def __call__(self, name: str) -> str:
        return f"{self.lead}pii_{name}"


def redact(docs: DataFrame) -> DataFrame:
    """docs with every span of text replaced by its kind in brackets, and n_chars brought up to date. All columns stay."""
    labels = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])
    held = {c: f"_kept{i}" for i, c in enumerate(docs.columns) if c not in ("text", "n_chars")}
    found = find_spans(docs.withColumnsRenamed(held))
    spans = F.array_sort(F.transform(F.concat(BASE, ADDED), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind_no"].alias("kind_no"))))

    def add(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        piece = F.concat(F.substring(F.col("text"), acc["at"] + 1, s["start"] - acc["at"]), F.element_at(labels, s["kind_no"] + 1))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(fresh, F.concat(acc["out"], piece)).otherwise(acc["out"]).alias("out"))

    text = F.aggregate(spans, F.struct(F.lit(0).alias("at"), F.lit("").alias("out")), add, lambda acc: F.concat(acc["out"], F.substring(F.col("text"), acc["at"] + 1, F.length("text"))))
    out = found.withColumn("text", F.when(F.size(BASE) + F.size(ADDED) > 0, text).otherwise(F.col("text")))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.drop(BASE, ADDED).withColumnsRenamed({v: k for k, v in held.items()}).select(*docs.columns)


def op7_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """n_<kind> counts base spans; n_added those that the trees add; spans holds both."""
    found = find_spans(table(spark, sf_dir, "documents").select("doc_id", "text"))
    names = F.array(*map(F.lit, KINDS))
    said = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind_no"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")
    counts = [F.size(F.filter("base_spans", _of_kind(i))).cast("long").alias(f"n_{k}") for i, k in enumerate(KINDS)]
    return found.select(
        "doc_id",
        *counts,
        F.sha2(said(F.col("base_spans")), 256).alias("base_sha256"),
        said(F.array_sort(F.concat("base_spans", "added_spans"))).alias("spans"),
        F.size("added_spans").cast("long").alias("n_added"),
    )
