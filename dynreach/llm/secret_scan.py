"""Secret scan through a trigram inverted index, with DataFrame functions alone.

Each rule's regular expression is turned into a Boolean trigram query: an OR of clauses, each the
trigrams that a match must hold. Postings are kept for the trigrams that the rules ask for. A
text's postings are intersected per clause, and only the texts left are verified with the rule; a
rule without a mandatory trigram is run over every text.

Postings are keyed by a hash of the text, so equal texts share them and a hash shared by different
texts costs a verification and nothing else. Trigrams are those of the text with A-Z in lower
case. Defined cases: null text is empty and has no spans; repeated rows give repeated results;
extra columns pass through whatever their names are; texts are scanned whole.
"""

from __future__ import annotations

from dataclasses import dataclass
from re import _constants as C
from re import _parser

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dynreach.llm.common import HOT_SHARE, cut

#: More strings than this in a set, and it is kept as trigrams only.
MOST_STRINGS = 64
#: Larger classes stand for any character.
MOST_OF_CLASS = 6
SPANS = "array<struct<start:int,order:int,kind:string,end:int>>"


@dataclass(frozen=True)
class Rule:
    """A kind of secret: matches of the pattern whose measured part is long enough."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1


#: The base rules, then public token formats.
BASE_RULES = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", r"[0-9a-f]+", 0, 24),
)
MORE_RULES = (
    Rule("private_key", r"-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]+"),
)


def trigram_query(pattern: str) -> list[frozenset[str]] | None:
    """Clauses of which a matching text holds one whole; None if nothing is mandatory."""
    clauses = _tighten(_clauses(list(_parser.parse(pattern))))
    return clauses if clauses and all(clauses) else None


def _tighten(clauses: list[frozenset[str]]) -> list[frozenset[str]]:
    """A clause that holds another whole adds nothing."""
    distinct = sorted(set(clauses), key=lambda c: (len(c), sorted(c)))
    return [c for i, c in enumerate(distinct) if not any(d <= c for d in distinct[:i])]


def _strings(item) -> set[str] | None:
    """All strings that an item can match, if few."""
    op, arg = item
    if op is C.LITERAL:
        return {chr(arg).lower()}
    if op is C.IN and all(o is C.LITERAL for o, _ in arg):
        found = {chr(a).lower() for _, a in arg}
        return found if len(found) <= MOST_OF_CLASS else None
    if op is C.SUBPATTERN:
        return _sequence(arg[-1])
    if op is C.BRANCH:
        parts = [_sequence(b) for b in arg[1]]
        found = set().union(*parts) if None not in parts else None
        return found if found is not None and len(found) <= MOST_STRINGS else None
    if op is C.MAX_REPEAT and arg[:2] == (0, 1):
        inner = _sequence(arg[2])
        return None if inner is None else inner | {""}
    return None


def _sequence(items) -> set[str] | None:
    out = {""}
    for item in items:
        found = _strings(item)
        if found is None:
            return None
        out = {a + b for a in out for b in found}
        if len(out) > MOST_STRINGS:
            return None
    return out


def _clauses(items) -> list[frozenset[str]]:
    """Runs of items with known strings give clauses; other items part the runs."""
    result, run = [frozenset()], {""}

    def both(more: list[frozenset[str]]) -> None:
        nonlocal result
        result = _tighten([a | b for a in result for b in more])

    def close() -> None:
        nonlocal run
        both([frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in run])
        run = {""}

    for item in items:
        found = _strings(item)
        if found is not None and len(run) * len(found) > MOST_STRINGS:
            close()
        if found is not None:
            run = {a + b for a in run for b in found}
            continue
        close()
        op, arg = item
        if op is C.SUBPATTERN:
            both(_clauses(arg[-1]))
        elif op is C.BRANCH:
            both(_tighten([c for b in arg[1] for c in _clauses(b)]))
        elif op in (C.MAX_REPEAT, C.MIN_REPEAT) and arg[0] >= 1:
            both(_clauses(arg[2]))
    close()
    return result


def folded(text: Column) -> Column:
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def postings(docs: DataFrame, rules: tuple[Rule, ...], text_col: str = "text") -> DataFrame:
    """(trigram, key): the texts that hold each trigram the rules ask for."""
    asked = sorted({t for r in rules for c in trigram_query(r.pattern) or [] for t in c})
    low = docs.select(F.xxhash64(text_col).alias("key"), folded(F.col(text_col)).alias("low")).where("low is not null")
    held = F.array_compact(F.array(*[F.when(F.col("low").contains(t), F.lit(i)) for i, t in enumerate(asked)]))
    rows = low.select("key", F.explode(held).alias("number"))
    return rows.select("key", "number", F.element_at(F.array(*map(F.lit, asked)), F.col("number") + 1).alias("trigram"))


def candidates(index: DataFrame, rules: tuple[Rule, ...]) -> DataFrame:
    """(key, rules): for each text, the rules of which a clause lies whole in its postings."""
    queries = [(k, trigram_query(r.pattern)) for k, r in enumerate(rules)]
    asked = sorted({t for _, q in queries for c in q or [] for t in c})
    number = {t: i for i, t in enumerate(asked)}
    words = -(-len(asked) // 60)
    bits = [
        F.bit_or(F.when((F.col("number") >= 60 * w) & (F.col("number") < 60 * (w + 1)), F.expr(f"shiftleft(1L, cast(number - {60 * w} as int))")).otherwise(F.lit(0).cast("long"))).alias(f"w{w}")
        for w in range(words)
    ]
    held = index.groupBy("key").agg(*bits)

    def whole(clause: frozenset[str]) -> Column:
        ok = F.lit(True)
        for w in range(words):
            mask = sum(1 << (number[t] - 60 * w) for t in clause if 60 * w <= number[t] < 60 * (w + 1))
            if mask:
                ok = ok & (F.col(f"w{w}").bitwiseAND(F.lit(mask)) == F.lit(mask))
        return ok

    named = []
    for k, q in queries:
        if q:
            any_clause = whole(q[0])
            for c in q[1:]:
                any_clause = any_clause | whole(c)
            named.append(F.when(any_clause, F.lit(1 << k)).otherwise(F.lit(0)))
    total = named[0]
    for x in named[1:]:
        total = total + x
    return held.select("key", total.alias("rules")).where("rules > 0")


def spans(text: Column, rule: Rule, order: int) -> Column:
    """Leftmost non-overlapping matches as structs (start, order, kind, end), in code points.

    The pieces between matches and the matches' lengths give the places.
    """
    pattern = F.lit(rule.pattern)
    found = F.regexp_extract_all(text, pattern, F.lit(0))
    between = F.split(text, rule.pattern, -1)
    steps = F.zip_with(F.slice(between, 1, F.size(found)), found, lambda gap, m: F.struct(F.length(gap).alias("gap"), F.length(m).alias("n"), m.alias("m")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(SPANS).alias("out"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + x["gap"]
        end = begin + x["n"]
        part = F.regexp_extract(x["m"], rule.pattern, rule.group) if rule.group else x["m"]
        one = F.array(F.struct(begin.alias("start"), F.lit(order).alias("order"), F.lit(rule.kind).alias("kind"), end.alias("end")))
        out = F.when(F.length(part) >= rule.least, F.concat(acc["out"], one)).otherwise(acc["out"])
        return F.struct(end.alias("at"), out.alias("out"))

    return F.aggregate(steps, start, step, lambda acc: acc["out"])


def _scanned(docs: DataFrame, rules: tuple[Rule, ...], text_col: str) -> DataFrame:
    """__row (the input's row whole, so that no name clashes), __text and __spans.

    Documents meet their candidates by a hash of the text. Null texts, and texts that more than one in HOT_SHARE
    documents hold (so fewer than HOT_SHARE), get their candidates by broadcast and are spread over all tasks.
    """
    wanted = cut(candidates(postings(docs, rules, text_col), rules))
    hashed = docs.select(F.xxhash64(text_col).alias("key"), F.col(text_col).isNull().alias("none"))
    copies = hashed.where("not none").groupBy("key").agg(F.count("*").alias("n"))
    total = copies.agg(F.sum("n")).first()[0] or 0
    hot = cut(copies.where(F.col("n") * HOT_SHARE > total).where(F.lit(total > HOT_SHARE)).join(wanted, "key", "left").select(F.col("key").alias("__key"), F.coalesce("rules", F.lit(0)).alias("__hot")))
    keyed = docs.select(F.struct(*[F.col(c) for c in docs.columns]).alias("__row"), F.xxhash64(text_col).alias("__key")).join(F.broadcast(hot), "__key", "left")
    apart = F.col("__hot").isNotNull() | F.col("__row").getField(text_col).isNull()
    keyed = keyed.withColumn("__turn", F.when(apart, F.pmod(F.monotonically_increasing_id(), F.lit(1 << 20)) + 1).otherwise(F.lit(0)))
    mine = wanted.select(F.col("key").alias("__key"), F.lit(0).cast("long").alias("__turn"), F.col("rules").alias("__rules"))
    joined = keyed.join(mine, ["__key", "__turn"], "left")
    held = F.coalesce("__hot", "__rules", F.lit(0))
    text, parts = F.col("__text"), []
    for k, rule in enumerate(rules):
        test = held.bitwiseAND(F.lit(1 << k)) != 0 if trigram_query(rule.pattern) else text.rlike(at_least(rule))
        parts.append(F.when(test, spans(text, rule, k)).otherwise(F.array().cast(SPANS)))
    joined = joined.withColumn("__text", F.coalesce(F.col("__row").getField(text_col), F.lit("")))
    return joined.select("__row", "__text", F.array_sort(F.concat(*parts)).alias("__spans"))


def scan(docs: DataFrame, rules: tuple[Rule, ...] = BASE_RULES + MORE_RULES, text_col: str = "text") -> DataFrame:
    """The input's rows with `secret_spans`: array of (start, order, kind, end) by start, then rule; replaces a column of that name."""
    found = _scanned(docs, rules, text_col)
    return found.select(*[F.col("__row").getField(c).alias(c) for c in docs.columns if c != "secret_spans"], F.col("__spans").alias("secret_spans"))


def at_least(rule: Rule) -> str:
    """A quick test that a full scan makes before it looks for places."""
    if rule.group == 0 and rule.pattern.endswith("+") and rule.least > 1 and rule.pattern.startswith("["):
        return rule.pattern[:-1] + "{%d}" % rule.least
    return rule.pattern


def joined_spans(found: Column) -> Column:
    return F.array_join(F.transform(found, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, rules: tuple[Rule, ...] = BASE_RULES + MORE_RULES, text_col: str = "text", mask: str = "[secret]") -> DataFrame:
    """Documents with every span replaced; spans that overlap are replaced together. Columns stay as they are."""
    found = _scanned(docs, rules, text_col)
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    text = F.col("__text")

    def step(acc: Column, s: Column) -> Column:
        gap = s["start"] - acc["at"]
        more = F.when(gap >= 0, F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.greatest(gap, F.lit(0))), F.lit(mask))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), more.alias("out"))

    clean = F.aggregate("__spans", start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text))))
    own = {c: F.col("__row").getField(c) for c in docs.columns}
    own[text_col] = F.when(F.size("__spans") > 0, clean).otherwise(own[text_col])
    return found.select(*[x.alias(c) for c, x in own.items()])


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, counts of the base kinds, base_sha256 and all spans."""
    found = scan(docs)
    of = lambda kind: F.size(F.filter("secret_spans", lambda s: s["kind"] == kind)).cast("long")
    base = F.filter("secret_spans", lambda s: s["order"] < len(BASE_RULES))
    return found.select(
        "doc_id", *[of(r.kind).alias(f"n_{r.kind}") for r in BASE_RULES], F.sha2(joined_spans(base), 256).alias("base_sha256"), joined_spans(F.col("secret_spans")).alias("spans")
    )
