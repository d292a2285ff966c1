"""Secret scans through a trigram inverted index, in DataFrame operations only.

From each rule's regular expression comes a Boolean query over trigrams that
every match must hold. The index lists, for each trigram that a query asks
for, the texts that hold it; intersecting those lists as the queries say gives
the candidates, and only they are searched. A rule without a mandatory trigram
is searched for in every text.
"""

from __future__ import annotations

import re._constants as sre
import re._parser as regex_parser
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .packed import cut

#: Candidates, or secrets to cut out, up to this many are broadcast (24 bytes each); more are joined by a shuffle.
BROADCAST_ROWS = 1_000_000
#: Matches of a text whose places are summed up together; sums of such runs are added in turn.
RUN = 256
#: Character classes up to this size count as alternatives when queries are derived.
CLASS = 8


@dataclass(frozen=True)
class Rule:
    """A kind of secret: leftmost non-overlapping matches of `pattern` whose `group` has `least` characters."""

    kind: str
    pattern: str
    group: int = 0
    least: int = 1
    base: bool = False


# The kinds of secret and the texts they have.
RULES = (
    Rule("assign", r"(?i)(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", 2, 6, True),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20, True),
    Rule("hex", r"[0-9a-f]+", 0, 24, True),
    Rule("private", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
    Rule("forge", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chat", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("cloud", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("payment", r"sk_live_[A-Za-z0-9]{16,}"),
)

Query = tuple[tuple[frozenset[str], ...], ...]


def trigram_query(pattern: str) -> Query:
    """What a match must hold, in lower case: all of the parts; of a part, all trigrams of one alternative.

    Literals, short classes, options of one character and alternations of
    such extend the alternatives at hand; anything else ends them. A part
    with an alternative shorter than a trigram says nothing and is left out,
    so an empty query means that nothing is mandatory.
    """
    def literals(op, arg) -> set[str] | None:
        """Every string that one element may match, if few."""
        if op is sre.LITERAL:
            return {chr(arg).lower()}
        if op is sre.IN:
            chars = set()
            for kind, value in arg:
                if kind is sre.LITERAL:
                    chars.add(chr(value).lower())
                elif kind is sre.RANGE and value[1] - value[0] < CLASS:
                    chars |= {chr(c).lower() for c in range(value[0], value[1] + 1)}
                else:
                    return None
            return chars if len(chars) <= CLASS else None
        if op is sre.MAX_REPEAT and arg[0] in (0, 1) and arg[1] == 1:
            inner = strings(arg[2])
            return inner and inner | ({""} if arg[0] == 0 else set())
        if op is sre.SUBPATTERN:
            return strings(arg[3])
        if op is sre.BRANCH:
            parts = [strings(x) for x in arg[1]]
            return set().union(*parts) if all(parts) else None
        return None

    def strings(items) -> set[str] | None:
        out = {""}
        for op, arg in items:
            got = literals(op, arg)
            if got is None or len(out) * len(got) > 64:
                return None
            out = {a + b for a in out for b in got}
        return out

    query, now = [], {""}
    for op, arg in [*regex_parser.parse(pattern), (None, None)]:
        got = literals(op, arg)
        if got is not None and len(now) * len(got) <= 64:
            now = {a + b for a in now for b in got}
            continue
        if min(map(len, now)) >= 3:
            options = {frozenset(s[k : k + 3] for k in range(len(s) - 2)) for s in now}
            query.append(tuple(sorted((o for o in options if not any(p < o for p in options)), key=sorted)))
        now = got or {""}
    return tuple(query)


def index(docs: DataFrame, trigrams: list[str], key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, print, trigram): the inverted index of the given trigrams over lower-cased texts."""
    low = docs.select(F.col(key), F.xxhash64(text).alias("print"), F.lower(text).alias("low"))
    held = F.array_compact(F.array(*(F.when(F.contains("low", F.lit(t)), F.lit(t)) for t in trigrams)))
    return low.select(key, "print", F.explode(held).alias("trigram"))


def candidates(postings: DataFrame, queries: dict[str, Query], key: str = "doc_id") -> DataFrame:
    """(key, print, kinds): the texts that the posting lists leave for each query."""
    def meets(query: Query) -> Column:
        out = F.lit(True)
        for part in query:
            one = F.lit(False)
            for option in part:
                one = one | F.array_contains(F.transform(F.array(F.array_except(F.array(*map(F.lit, sorted(option))), F.col("held"))), F.size), 0)
            out = out & one
        return out

    held = postings.groupBy(key, "print").agg(F.collect_set("trigram").alias("held"))
    kinds = F.array_compact(F.array(*(F.when(meets(q), F.lit(kind)) for kind, q in queries.items())))
    return held.select(key, "print", kinds.alias("kinds")).where(F.size("kinds") > 0)


def _matches(text: Column, rule: Rule) -> Column:
    """What stands before each match and how long it and its group are, as parallel arrays."""
    pattern = F.lit(rule.pattern)
    length = lambda x: F.char_length(x)
    return F.struct(
        F.lit(rule.kind).alias("kind"), F.lit(rule.least).alias("least"),
        F.transform(F.split(text, rule.pattern, -1), length).alias("gaps"),
        F.transform(F.regexp_extract_all(text, pattern, F.lit(0)), length).alias("sizes"),
        F.transform(F.regexp_extract_all(text, pattern, F.lit(rule.group)), length).alias("groups"),
    )


def _placed(m: Column) -> Column:
    """The places (start, end) of the good matches in what `_matches` gives, within the row.

    Running sums over runs of RUN matches, then over the runs, so that a text
    with very many matches costs little more than its matches.
    """
    matches = F.arrays_zip(F.slice(m["gaps"], 1, F.size(m["sizes"])).alias("gap"), m["sizes"].alias("size"), m["groups"].alias("part"))
    none = F.array().cast("array<struct<start:bigint,end:bigint,good:boolean>>")
    start = F.struct(F.lit(0).cast("bigint").alias("at"), none.alias("out"))

    def add(acc: Column, x: Column) -> Column:
        to = acc["at"] + x["gap"] + x["size"]
        return F.struct(to.alias("at"), F.concat(acc["out"], F.array(F.struct((to - x["size"]).alias("start"), to.alias("end"), (x["part"] >= m["least"]).alias("good")))).alias("out"))

    def join(acc: Column, run: Column) -> Column:
        good = F.transform(F.filter(run["out"], lambda x: x["good"]), lambda x: F.struct((x["start"] + acc["at"]).alias("start"), (x["end"] + acc["at"]).alias("end"), x["good"].alias("good")))
        return F.struct((acc["at"] + run["at"]).alias("at"), F.concat(acc["out"], good).alias("out"))

    n = F.ceil(F.size(m["sizes"]) / RUN).cast("int")
    runs = F.transform(F.sequence(F.lit(0), n - 1), lambda k: F.aggregate(F.slice(matches, k * RUN + 1, F.lit(RUN)), start, add))
    return F.when(n > 0, F.aggregate(runs, start, join)["out"]).otherwise(none)


def _found(docs: DataFrame, key: str, text: str, rules: tuple[Rule, ...]) -> DataFrame:
    """(key, print, secrets) of the texts that hold secrets: structs (start, rank, kind, end) in text order."""
    queries = {r.kind: trigram_query(r.pattern) for r in rules}
    asked = {k: q for k, q in queries.items() if q}
    trigrams = sorted({t for q in asked.values() for part in q for option in part for t in option})
    source = docs.select(F.col(key), F.xxhash64(text).alias("print"), F.coalesce(text, F.lit("")).alias("text"))
    found = None
    for rule in rules:
        if not queries[rule.kind]:
            run = rule.pattern.removesuffix("+") + f"{{{rule.least}}}" if rule.group == 0 and rule.pattern.endswith("]+") else rule.pattern
            part = source.where(F.col("text").rlike(run)).select(key, "print", _matches(F.col("text"), rule).alias("m"))
            found = part if found is None else found.unionByName(part)
    if asked:
        chosen = cut(candidates(index(docs, trigrams, key, text), asked, key)).select(F.col(key).alias("ck"), F.col("print").alias("cp"), "kinds")
        if chosen.count() <= BROADCAST_ROWS:
            chosen = F.broadcast(chosen)
        fetched = source.join(chosen, F.col(key).eqNullSafe(F.col("ck")) & (F.col("print") == F.col("cp")))
        per_rule = F.array_compact(F.array(*(F.when(F.array_contains("kinds", r.kind), _matches(F.col("text"), r)) for r in rules if r.kind in asked)))
        part = fetched.select(key, "print", F.explode(per_rule).alias("m"))
        found = part if found is None else found.unionByName(part)
    rank = F.array_position(F.array(*(F.lit(r.kind) for r in rules)), F.col("m.kind")).cast("int")
    each = found.select(key, "print", rank.alias("rank"), F.col("m.kind").alias("kind"), _placed(F.col("m")).alias("at")).where(F.size("at") > 0)
    named = F.transform("at", lambda x: F.struct(x["start"].alias("start"), F.col("rank").alias("rank"), F.col("kind").alias("kind"), x["end"].alias("end")))
    # A kind has one array for a text, so rows that repeat a text collapse in the set.
    return each.select(key, "print", named.alias("own")).groupBy(key, "print").agg(F.array_sort(F.flatten(F.collect_set("own"))).alias("secrets"))


def spans(docs: DataFrame, key: str = "doc_id", text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(key, print, kind, start, end): every secret, in code points, end exclusive.

    `print` is a hash of the text, so rows that share an id stay apart, and
    rows that repeat both give their secrets once.
    """
    return _found(docs, key, text, rules).select(key, "print", F.explode("secrets").alias("s")).select(key, "print", "s.kind", "s.start", "s.end")


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """(key, print, secrets) of every row; secrets are structs (start, rank, kind, end) in text order.

    rank is the place of the kind among the rules. Null and empty texts have
    no secrets. Repeated rows each get the same result; a null id is kept. An
    empty table gives no rows; other columns are not read.
    """
    found = _found(docs, key, text, rules).withColumnsRenamed({key: "k", "print": "p"})
    rows = docs.select(F.col(key), F.xxhash64(text).alias("print"))
    none = F.array().cast("array<struct<start:bigint,rank:int,kind:string,end:bigint>>")
    return rows.join(found, F.col(key).eqNullSafe(F.col("k")) & (F.col("print") == F.col("p")), "left").select(key, "print", F.coalesce("secrets", none).alias("secrets"))


def listed(secrets: Column, kinds: list[str] | None = None) -> Column:
    """kind:start:end of the secrets, comma-joined; of some kinds only, if given."""
    chosen = F.filter(secrets, lambda x: x["kind"].isin(kinds)) if kinds else secrets
    return F.array_join(F.transform(chosen, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")


def redact(docs: DataFrame, key: str = "doc_id", text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The same rows and columns, with every secret of the text replaced by its kind in angle brackets.

    Overlapping secrets become one mark, that of the first. Texts without
    secrets, nulls and repeated rows stay as they are.
    """
    to_cut = cut(_found(docs, key, text, rules).withColumnsRenamed({key: "__k", "print": "__p", "secrets": "__secrets"}))
    if (to_cut.agg(F.sum(F.size("__secrets"))).first()[0] or 0) <= BROADCAST_ROWS:
        to_cut = F.broadcast(to_cut)
    state = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast("array<string>").alias("out"))
    body = lambda lo, hi: F.substring(F.col(text), (lo + 1).cast("int"), (hi - lo).cast("int"))
    step = lambda acc, x: F.when(x["start"] >= acc["at"], F.struct(x["end"].alias("at"), F.concat(acc["out"], F.array(body(acc["at"], x["start"]), F.concat(F.lit("<"), x["kind"], F.lit(">")))).alias("out"))).otherwise(F.struct(F.greatest(acc["at"], x["end"]).alias("at"), acc["out"].alias("out")))
    done = lambda acc: F.concat(F.array_join(acc["out"], ""), body(acc["at"], F.char_length(text).cast("bigint")))
    clean = F.when(F.col("__secrets").isNull(), F.col(text)).otherwise(F.aggregate("__secrets", state, step, done))
    marked = docs.withColumn("__print", F.xxhash64(text))
    joined = marked.join(to_cut, F.col(key).eqNullSafe(F.col("__k")) & (F.col("__print") == F.col("__p")), "left")
    return joined.select(*(clean.alias(c) if c == text else F.col(c) for c in docs.columns))
