"""Personal data by weak supervision.

Patterns propose candidate spans: the base patterns of the contract, looser ones of the same four kinds (spelled-out
addresses, national phone numbers, 15-digit cards, long ip addresses), and secrets that are assigned to a name. Four
labelers vote for or against each candidate or abstain: the regular expression with its format check (which abstains
on looser candidates that pass, as their pattern proves little), a gazetteer (domains, country codes, issuer digits,
reserved nets, sizes of keys), the words in front, and the characters beside it. Counts of each combination of votes,
kind and looseness are summed over the whole table; there are at most 810 combinations. On these counts
expectation-maximisation estimates how often each labeler is right when it votes and how likely each combination is
personal data, and a logistic span classifier over kind, looseness and votes is trained on those estimates. Base spans
that pass their check are always kept; of the other candidates those stay that the classifier accepts and that touch
no base span.

Texts are searched and judged by native expressions only; candidates are written once, so texts are read once.

Defined results: null counts as empty; a table without candidates gives rows without spans; texts of any length are
searched whole; repeated rows are judged each; the base patterns take the leftmost match of each kind and never retry
after a failed check; an empty table gives an empty result; other columns of the input are ignored, whatever their names.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, filled
from .spans import found

KINDS = ("email", "ip", "card", "phone", "secret")
EMAIL, IP, CARD, PHONE, SECRET = range(5)
BASE_KINDS = 4

# Each takes the leftmost longest match; the look-behinds and possessive repeats keep long runs linear and change no match.
STRICT = {
    EMAIL: r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    IP: r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    CARD: r"[0-9](?:[\x20-]?[0-9]){15,}+",
    PHONE: r"\+[0-9][\x20().0-9-]+[0-9]",
}
LOOSE = [
    (EMAIL, r"(?i)(?<![a-z0-9._%+-])[a-z0-9._%+-]{1,64}+ ?[\[(]at[\])] ?[a-z0-9-]{1,63}+(?: ?[\[(]dot[\])] ?[a-z0-9-]{1,63}+){1,4}"),
    (IP, r"(?i)(?<![0-9a-f:])(?:[0-9a-f]{1,4}:){7}[0-9a-f]{1,4}(?![0-9a-f:])"),
    (CARD, r"(?<![0-9])3[47][0-9]{2}[\x20-]?[0-9]{6}[\x20-]?[0-9]{5}(?![0-9])"),
    (PHONE, r"(?<![0-9A-Za-z+().-])(?:\([0-9]{3}\) ?|[0-9]{3}[.-])[0-9]{3}[.-][0-9]{4}(?![0-9A-Za-z])"),
    (SECRET, r"(?i)(?<![a-z0-9])(?:token|secret|passw(?:or)?d|(?:api|access|private)[_ -]?key|authorization)[\x20_a-z-]{0,20}+ ?[:=] ?[\"']?+(?:bearer )?+[a-z0-9+/_.=-]{16,}+"),
]
OCTET = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
DOMAINS = "com|org|net|edu|gov|mil|int|info|biz|io|co|de|fr|es|it|nl|uk|us|ca|eu|ch|at|be|pl|se|no|dk|fi|pt|br|mx|ar|jp|cn|in|au|ru"
COUNTRIES = "1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|21[1-8]|35[0-9]|37[0-9]|38[0-9]|42[0-3]|85[2356]|97[0-9]"
CONTEXT = {
    EMAIL: r"(?i)(?:e-?mail|contact|write to|kontakt|correo|courriel|adresse)",
    IP: r"(?i)(?:\bip\b|address|host|server|login|adresse|direcci)",
    CARD: r"(?i)(?:card|visa|mastercard|amex|credit|debit|carte|tarjeta|karte)",
    PHONE: r"(?i)(?:\btel|phone|call|fax|mobile|cell|telefon|t[ée]l[ée]phone|llam)",
    SECRET: r"(?i)(?:config|credential|export|env|login|header)",
}
#: Just in front of numbers that name a thing and no person.
THING = r"(?i)\b(?:part|ref|version|ver|order|item|sku|serial|isbn|issn|doi|section|chapter|figure|table|page|build|release|invoice|model|id|no|nr|number)[\x20.:#]{1,3}$"
CONTEXT_POINTS = 40
#: Levels of each field of a candidate's signature; the first four are votes, shifted by one.
FIELDS = {"regex": 3, "gazetteer": 3, "context": 3, "edges": 3, "kind": 5, "loose": 2}
VOTES = 4


def digits_of(hit: Column) -> Column:
    return F.regexp_replace(hit, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """Whether the digits pass the check in which every second one from the right counts double."""
    n = F.length(digits)

    def add(total: Column, i: Column) -> Column:
        d = F.substring(digits, i, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return total + F.when((n - i) % 2 == 1, twice).otherwise(d)

    return F.when(n > 0, F.aggregate(F.sequence(F.lit(1), n), F.lit(0), add) % 10 == 0).otherwise(False)


def passes(kind: int, hit: Column) -> Column:
    """The format check of a kind."""
    digits = digits_of(hit)
    if kind == EMAIL:
        return F.lit(True)
    if kind == IP:
        return F.regexp_like(hit, F.lit(rf"^(?:{OCTET}\.){{3}}{OCTET}$"))
    if kind == CARD:
        return F.when(F.length(digits).between(16, 19), luhn(digits)).otherwise(False)
    return F.length(digits).between(8, 15)


def _vote(yes: Column, no: Column | None = None) -> Column:
    return F.when(yes, 1).otherwise(0) if no is None else F.when(yes, 1).when(no, -1).otherwise(0)


def _regex(kind: int, hit: Column, strict: bool) -> Column:
    """The vote of the regular expression and its format check."""
    like = lambda p: F.regexp_like(hit, F.lit(p))
    if strict:
        ok = passes(kind, hit) & like(r"[A-Za-z]{2,}$") if kind == EMAIL else passes(kind, hit)
        return _vote(ok, ~ok)
    if kind == CARD:
        ok = luhn(digits_of(hit))
        return _vote(ok, ~ok)
    if kind == SECRET:
        value = F.regexp_extract(hit, "[A-Za-z0-9+/_.=-]+$", 0)
        ok = F.regexp_like(value, F.lit("[0-9].*[0-9].*[0-9]")) & F.regexp_like(value, F.lit("[A-Za-z]")) & (F.length(value) >= 20)
        return _vote(ok, ~ok)
    never = F.lit(False)
    if kind == EMAIL:
        return _vote(never, ~like(r"[A-Za-z]{2,}$"))
    if kind == IP:
        return _vote(never, ~like("[0-9A-Fa-f]{3,}"))
    return _vote(never, ~F.regexp_like(digits_of(hit), F.lit("^[2-9][0-9]{2}[2-9]")))


def _gazetteer(kind: int, hit: Column) -> Column:
    like = lambda p: F.regexp_like(hit, F.lit(p))
    if kind == EMAIL:
        return _vote(like(rf"(?i)[.\])] ?(?:{DOMAINS})$"))
    if kind == IP:
        return _vote(like("(?i)^(?:2[0-9a-f]{3}|fd[0-9a-f]{2}|fe80):"), like(r"^(?:0+|127|255)\."))
    if kind == CARD:
        return _vote(like("^[3-6]"), like("^[^3-6]"))
    if kind == SECRET:
        return _vote(like(r"(?i)(?:(?<![0-9a-f])(?:[0-9a-f]{32}|[0-9a-f]{40}|[0-9a-f]{64})|akia[0-9a-z]{16}|(?:gh[pousr]|xox[abp]|sk|pk)[_-][0-9a-z_-]{16,}|ey[0-9a-z_-]+\.[0-9a-z_.-]+)$"))
    return _vote(like(rf"^(?:\+(?:{COUNTRIES})|\()"), like(r"^\+(?:0|999)"))


def _candidates(kind: int, pattern: str, gate: Column, strict: bool) -> Column:
    text = F.col("text")

    def judged(x: Column) -> Column:
        front = F.substring(text, F.greatest(x.start - CONTEXT_POINTS + 1, F.lit(1)), F.least(x.start, F.lit(CONTEXT_POINTS)))
        wordy = F.lit(r"^[\p{L}\p{N}]$")
        glued = (F.regexp_like(F.substring(text, x.start, F.lit(1)), wordy) & (x.start > 0)) | F.regexp_like(F.substring(text, x.end + 1, F.lit(1)), wordy)
        thing = F.regexp_like(front, F.lit(THING))
        return F.struct(
            F.lit(kind).alias("kind"),
            x.start.alias("start"),
            x.end.alias("end"),
            (passes(kind, x.hit) if strict else F.lit(False)).alias("base"),
            _regex(kind, x.hit, strict).alias("regex"),
            _gazetteer(kind, x.hit).alias("gazetteer"),
            F.when(thing, -1).otherwise(_vote(F.regexp_like(front, F.lit(CONTEXT[kind])))).alias("context"),
            _vote(F.lit(False), glued).alias("edges"),
            F.lit(int(not strict)).alias("loose"),
        )

    return F.transform(found(text, pattern, gate), judged)


def candidates(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(doc_id, spans): every candidate with its place, votes and surroundings."""
    rows = docs.select(F.col(id_column).alias("doc_id"), filled(text_column).alias("text"))
    rows = rows.select("doc_id", "text", F.regexp_like("text", F.lit("[0-9]")).alias("digit"), F.contains(F.col("text"), F.lit("@")).alias("sign"), F.regexp_like("text", F.lit(r"(?i)[\[(]at[\])]")).alias("spelled"))
    digit = F.col("digit")
    gates = {EMAIL: F.col("sign"), IP: digit, CARD: digit, PHONE: digit & F.contains(F.col("text"), F.lit("+"))}
    colon = F.contains(F.col("text"), F.lit(":"))
    loose_gates = {EMAIL: F.col("spelled"), IP: colon & digit, CARD: digit, PHONE: digit, SECRET: digit & (colon | F.contains(F.col("text"), F.lit("=")))}
    parts = [_candidates(k, STRICT[k], gates[k], True) for k in range(BASE_KINDS)] + [_candidates(k, p, loose_gates[k], False) for k, p in LOOSE]
    rows = rows.select("doc_id", F.concat(*parts).alias("all"))
    base = F.filter("all", lambda c: c.base)
    apart = F.filter("all", lambda c: c.base | ~F.exists("base_spans", lambda b: (b.start < c.end) & (c.start < b.end)))
    return rows.select("doc_id", "all", base.alias("base_spans")).select("doc_id", apart.alias("spans"))


def reliabilities(votes: np.ndarray, groups: np.ndarray, counts: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, np.ndarray]:
    """For rows of votes (-1, 0, 1) in a group, seen so often: the chance that a labeler that votes is right about what is
    and about what is not personal data (labelers x 2), and the chance that each row is personal data.

    It starts from the votes' majority, and where they tie or all abstain a little below one half, so a group without
    votes is held to be no personal data. The prior is the same for all labelers, right twice to wrong once; abstaining
    says nothing.
    """
    chance = 1 / (1 + np.exp(0.25 - votes.sum(1)))
    right = np.full((votes.shape[1], 2), 2 / 3)
    for _ in range(rounds):
        for j in range(votes.shape[1]):
            for c, weight in ((0, chance * counts), (1, (1 - chance) * counts)):
                yes, no = weight[votes[:, j] == (1, -1)[c]].sum(), weight[votes[:, j] == (-1, 1)[c]].sum()
                right[j, c] = (yes + 2) / (yes + no + 3)
        for_it = np.log(right[:, 0] / (1 - right[:, 1]))
        against = np.log((1 - right[:, 0]) / right[:, 1])
        logit = (votes == 1) @ for_it + (votes == -1) @ against
        for g in np.unique(groups):
            of = groups == g
            share = ((chance * counts)[of].sum() + 1) / (counts[of].sum() + 2)
            logit[of] += np.log(share / (1 - share))
        chance = 1 / (1 + np.exp(-np.clip(logit, -30, 30)))
    return right, chance


def span_classifier(signatures: np.ndarray, chance: np.ndarray, counts: np.ndarray, steps: int = 400, rate: float = 0.5, shrink: float = 0.02) -> tuple[list[list[float]], float]:
    """Weights by field and level, and the bias, of a logistic model fitted to the chances by gradient steps."""
    sizes = list(FIELDS.values())
    at = np.cumsum([0, *sizes[:-1]])
    x = np.zeros((len(signatures), sum(sizes)))
    for f in range(len(sizes)):
        x[np.arange(len(x)), at[f] + signatures[:, f]] = 1.0
    weight = np.log1p(counts)
    weight = weight / max(weight.sum(), 1e-9)
    w, b = np.zeros(x.shape[1]), 0.0
    for _ in range(steps):
        error = (1 / (1 + np.exp(-(x @ w + b))) - chance) * weight
        w -= rate * (x.T @ error + shrink * w / max(1, len(x)))
        b -= rate * error.sum()
    return [w[a : a + n].tolist() for a, n in zip(at, sizes, strict=True)], float(b)


def _levels(c: Column) -> list[Column]:
    return [c[f] + 1 if i < VOTES else c[f] for i, f in enumerate(FIELDS)]


def train(table: DataFrame) -> tuple[list[list[float]], float]:
    """The span classifier of a table of candidates; what comes back has one row for each combination of levels at most."""
    spans = table.select(F.explode("spans").alias("c"))
    rows = spans.groupBy(*(level.alias(f) for f, level in zip(FIELDS, _levels(F.col("c")), strict=True))).count().collect()
    if not rows:
        return [[0.0] * n for n in FIELDS.values()], -1.0
    rows = np.array(sorted(map(tuple, rows)), np.int64)
    signatures, counts = rows[:, :-1], rows[:, -1].astype(float)
    kind, loose = (signatures[:, list(FIELDS).index(f)] for f in ("kind", "loose"))
    _, chance = reliabilities(signatures[:, :VOTES] - 1, 2 * kind + loose, counts)
    return span_classifier(signatures, chance, counts)


def spans_found(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """(doc_id, base, kept): base spans, and all kept ones, as sorted arrays of (kind, start, end)."""
    table = cut(candidates(docs, id_column, text_column), "candidates")
    weights, bias = train(table)

    def accepted(c: Column) -> Column:
        score = F.lit(bias)
        for values, level in zip(weights, _levels(c), strict=True):
            score = score + F.get(F.array(*map(F.lit, values)), level)
        return c.base | (score >= 0)

    place = lambda c: F.struct(c.kind.alias("kind"), c.start.alias("start"), c.end.alias("end"))
    pick = lambda test: F.array_sort(F.array_distinct(F.transform(F.filter("spans", test), place)))
    return table.select("doc_id", pick(lambda c: c.base).alias("base"), pick(accepted).alias("kept"))


def _line(spans: str) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s.kind), s.start, s.end)), ",")


def find(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per row of docs: base counts, the digest of the base spans, all spans, and how many these are."""
    rows = spans_found(docs, id_column, text_column)

    def of_kind(k: int) -> Column:
        return F.size(F.filter("base", lambda s: s.kind == k)).cast("long").alias(f"n_{KINDS[k]}")

    return rows.select("doc_id", *map(of_kind, range(BASE_KINDS)), F.sha2(_line("base"), 256).alias("base_sha256"), _line("kept").alias("spans"), F.size("kept").cast("long").alias("n_spans"))
