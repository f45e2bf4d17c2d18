"""Personal data: exact base kinds, then bootstrapped contextual extraction.

Base spans of four kinds are known entities; words that look like keys or
digests are known as secrets, which alone makes no span of them.  The words
around a mention are its lexical patterns: one or two before, one or two
after, and a key inside the word, as in ``user=``.  Patterns and instances
form a graph: a pattern is as good as the share of all places it marks,
anywhere in the corpus, that hold known entities of its kind; an instance is
as good as the patterns that mark it, together.  Each round scores the graph,
tests every pattern, and lets what the good ones mark count as known in the
next, until a round adds nothing.

Everything is DataFrame functions.  Base patterns are written so that the
regex engine never rescans a run of characters: a match can only begin where a
run begins or where the last match ended, and runs are possessive, which
leaves the leftmost non-overlapping matches as they are.  Matches leave their
text as rows with the length of what lies before them, so places are running
sums and a text's cost grows with its length alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from arcfield.deploy import save

KINDS = ("email", "ip", "card", "phone")
#: A kind that only patterns can add.
SECRET = "secret"
# The base kinds
_LOCAL, _LABEL, _BLANK = r"[A-Za-z0-9._%+-]", r"[A-Za-z0-9-]", r"\x20\x09-\x0D"
PATTERNS = {
    "email": rf"(?:(?<!{_LOCAL})|\G){_LOCAL}++@{_LABEL}++(?:\.{_LABEL}++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    # a whole run of digits with single separators, 16 to 19 of them
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){15,18}+(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: An identifier is a word with a digit or an at sign.
IDENTIFIER = rf"(?<![^{_BLANK}])[^{_BLANK}0-9@]*+[0-9@][^{_BLANK}]*+"
#: The last two words before a mention and what touches it; the same after it; a key inside a word.
_BEFORE = rf"(?<![^{_BLANK}])(?:([^{_BLANK}]++)[{_BLANK}]++)?([^{_BLANK}]++)[{_BLANK}]++[^{_BLANK}]*+$"
_AFTER = rf"^[^{_BLANK}]*+[{_BLANK}]++([^{_BLANK}]++)(?:[{_BLANK}]++([^{_BLANK}]++))?"
_TOUCHING = rf"(?<![^{_BLANK}])[^{_BLANK}]++$"
_KEY = r"^[^=:]*+[=:](?=.)"
#: A secret as such has this many characters of the class, this many different ones, letters and digits.
SECRET_LENGTH, SECRET_VARIETY = 20, 10
_SECRET = rf"^(?=.*[0-9])(?=.*[A-Za-z])[A-Za-z0-9+/=_-]{{{SECRET_LENGTH},}}$"
#: Patterns that are broadcast, more are shuffled; distinct known entities and precision a pattern needs; belief an instance needs.
MOST_BROADCAST, MIN_KNOWN, MIN_PRECISION, MIN_BELIEF = 50_000, 4, 0.7, 0.85


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def luhn(m: Column) -> Column:
    back = F.reverse(_digits(m))

    def term(i: Column) -> Column:
        d = F.substring(back, i, F.lit(1)).cast("int")
        return F.when(i % 2 == 1, d).when(d > 4, 2 * d - 9).otherwise(2 * d)

    return F.aggregate(F.transform(F.sequence(F.lit(1), F.length(back)), term), F.lit(0), lambda a, b: a + b) % 10 == 0


def _valid(kind: str, m: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: F.coalesce(F.regexp_replace(p, "^0+(?=[0-9])", "").try_cast("int") <= 255, F.lit(False)))
    if kind == "card":
        return luhn(m)
    if kind == "phone":
        return F.length(_digits(m)).between(8, 15)
    return F.lit(True)


_HINT = {
    "email": lambda t: F.contains(t, F.lit("@")),
    "ip": lambda t: F.rlike(t, F.lit(r"[0-9]\.[0-9]")),
    "card": lambda t: F.rlike(t, F.lit(r"[0-9](?:[\x20-]?[0-9]){15}")),
    "phone": lambda t: F.contains(t, F.lit("+")),
    "loose": lambda t: F.rlike(t, F.lit("[0-9@]")),
}


def matches(docs: DataFrame) -> DataFrame:
    """(rid, doc_id, found): the matches of all base patterns and of identifiers in each row's text.

    ``found`` holds (kind, place, gap, m, touching, l1, l2, r1, r2): the match's
    number within its kind, the code points between it and the one before, its
    text and the words around it.
    """
    t = F.coalesce(F.col("text"), F.lit(""))
    out = docs.select(F.monotonically_increasing_id().alias("rid"), "doc_id", t.alias("text"))
    every = {**PATTERNS, "loose": IDENTIFIER}
    for kind, pattern in every.items():
        out = out.withColumn(f"m_{kind}", F.when(_HINT[kind](F.col("text")), F.regexp_extract_all("text", F.lit(pattern), F.lit(0))))
    # texts without a match are not split
    for kind, pattern in every.items():
        out = out.withColumn(f"g_{kind}", F.when(F.size(f"m_{kind}") > 0, F.split("text", pattern, -1)))
    out = out.withColumns({f"n_{kind}": F.slice(f"g_{kind}", F.lit(2), F.size(f"m_{kind}")) for kind in every})

    def piece(kind: str) -> Column:
        def one(x: Column, i: Column) -> Column:
            gap, after = x[f"g_{kind}"], x[f"n_{kind}"]
            fields = {"place": i, "gap": F.length(gap), "m": x[f"m_{kind}"], "touching": F.regexp_extract(gap, _TOUCHING, 0)}
            fields |= {"l1": F.regexp_extract(gap, _BEFORE, 2), "l2": F.regexp_extract(gap, _BEFORE, 1), "r1": F.regexp_extract(after, _AFTER, 1), "r2": F.regexp_extract(after, _AFTER, 2)}
            return F.struct(F.lit(kind).alias("kind"), *[v.alias(k) for k, v in fields.items()])

        zipped = F.filter(F.arrays_zip(f"m_{kind}", f"g_{kind}", f"n_{kind}"), lambda x: x[f"m_{kind}"].isNotNull())
        return F.coalesce(F.transform(zipped, one), F.array())

    return out.select("rid", "doc_id", F.concat(*map(piece, every)).alias("found"))


def placed(found: DataFrame) -> DataFrame:
    """(rid, kind, s, e, m, touching, l1, l2, r1, r2): spans in code points of ``matches`` rows, valid base ones and all identifiers."""
    rows = found.select("rid", F.explode("found").alias("x")).select("rid", "x.*").withColumn("n", F.length("m"))
    so_far = W.partitionBy("rid", "kind").orderBy("place").rowsBetween(W.unboundedPreceding, 0)
    rows = rows.withColumn("e", F.sum(F.col("gap") + F.col("n")).over(so_far).cast("int")).withColumn("s", F.col("e") - F.col("n"))
    fine = F.lit(True)
    for kind in ("ip", "card", "phone"):
        fine = F.when(F.col("kind") == kind, _valid(kind, F.col("m"))).otherwise(fine)
    return rows.where(fine).select("rid", "kind", "s", "e", "m", "touching", "l1", "l2", "r1", "r2")


def mentions(spans: DataFrame) -> DataFrame:
    """(rid, kind, s, e, m, contexts): base spans, and identifiers that no base span touches.

    An identifier is cut to its value, without a key and without signs at both
    ends; its kind is null, or secret where it looks like one.
    """
    base = F.col("kind") != "loose"
    up = W.partitionBy("rid").orderBy("s", ~base).rowsBetween(W.unboundedPreceding, 0)
    down = W.partitionBy("rid").orderBy(F.col("s").desc(), ~base).rowsBetween(W.unboundedPreceding, 0)
    rows = spans.withColumn("reach", F.max(F.when(base, F.col("e"))).over(up)).withColumn("next", F.min(F.when(base, F.col("s"))).over(down))
    free = (F.coalesce("reach", F.lit(0)) <= F.col("s")) & (F.col("next").isNull() | (F.col("next") >= F.col("e")))
    rows = rows.where(base | free)
    key = F.when(base, F.regexp_extract("touching", _KEY.replace("(?=.)", "$"), 0)).otherwise(F.regexp_extract("m", _KEY, 0))
    rows = rows.withColumn("key", key)
    value = F.substring("m", F.length("key") + 1, F.length("m"))
    lead = F.length(F.regexp_extract(value, r"^[^\p{L}\p{N}+@]*+", 0))
    body = F.regexp_replace(F.substring(value, lead + 1, F.length("m")), r"(?<=[\p{L}\p{N}])[^\p{L}\p{N}]++$", "")
    rows = rows.withColumn("body", F.when(base, F.col("m")).otherwise(body))
    start = F.when(base, F.col("s")).otherwise(F.col("s") + F.length("key") + lead)
    looks = F.rlike("body", F.lit(_SECRET)) & (F.size(F.array_distinct(F.split("body", ""))) >= SECRET_VARIETY)
    kind = F.when(base, F.col("kind")).when(looks, SECRET)
    rows = rows.select("rid", kind.alias("kind"), start.alias("s"), (start + F.length("body")).alias("e"), F.lower("body").alias("m"), _contexts("l1", "l2", "r1", "r2", "key").alias("contexts"))
    return rows.where(F.rlike("m", F.lit(r"[\p{L}\p{N}]")))


def _contexts(l1: str, l2: str, r1: str, r2: str, key: str) -> Column:
    """The patterns of one place: which words they are, then the words."""

    def some(mark: str, *words: str) -> Column:
        there = F.lit(True)
        for w in words:
            there = there & (F.length(w) > 0)
        return F.when(there, F.concat(F.lit(f"{mark} "), F.concat_ws(" ", *[F.lower(F.col(w)) for w in words])))

    return F.array_compact(F.array(some("<", l1), some("<<", l2, l1), some(">", r1), some(">>", r1, r2), some("=", key)))


def marked_places(docs: DataFrame, patterns: DataFrame, most: int = MOST_BROADCAST) -> DataFrame:
    """(context, places): how often each of ``patterns`` marks a word, over all texts.

    Up to ``most`` patterns are broadcast; more meet the counted places in a
    shuffle.
    """
    asked = patterns.select("context", F.split("context", " ").alias("p"))
    small = patterns.count() <= most
    t = F.lower(F.btrim(F.coalesce("text", F.lit("")), F.lit(" \t\n\x0b\x0c\r")))
    w = docs.select(F.split(t, rf"[{_BLANK}]++").alias("w"))
    none = F.lit("")
    w = w.select("w", F.concat(F.array(none), "w").alias("l1"), F.concat(F.array(none, none), "w").alias("l2"), F.slice("w", F.lit(2), F.size("w")).alias("r1"), F.slice("w", F.lit(3), F.size("w")).alias("r2"))
    w = w.select(F.inline(F.arrays_zip("w", "l1", "l2", "r1", "r2"))).where("w is not null").withColumn("key", F.regexp_extract("w", _KEY, 0))
    if not small:
        places = w.select(F.explode(_contexts("l1", "l2", "r1", "r2", "key")).alias("context"))
        return places.groupBy("context").agg(F.count("*").alias("places")).join(patterns.select("context"), "context")
    shapes = {"<": ("l1",), "<<": ("l2", "l1"), ">": ("r1",), ">>": ("r1", "r2"), "=": ("key",)}
    for k, (mark, names) in enumerate(shapes.items()):
        of_shape = asked.where(F.get("p", F.lit(0)) == mark).select(*[F.get("p", F.lit(i + 1)).alias(n) for i, n in enumerate(names)], F.col("context").alias(f"c{k}"))
        w = w.join(F.broadcast(of_shape), list(names), "left")
    held = F.coalesce(*[f"c{k}" for k in range(len(shapes))]).isNotNull()
    return w.where(held).select(F.explode(F.array_compact(F.array(*[f"c{k}" for k in range(len(shapes))]))).alias("context")).groupBy("context").agg(F.count("*").alias("places"))


def discover(docs: DataFrame, found: DataFrame, *, most: int = MOST_BROADCAST) -> DataFrame:
    """(rid, kind, s, e): spans of identifiers that high-confidence patterns mark.

    ``found`` is a stored table of ``mentions``.  Every context with enough
    known entities is tested; rounds go on until one adds nothing.
    """
    spark = found.sparkSession
    graph = found.select("kind", "m", F.explode("contexts").alias("context")).groupBy("context", "m", "kind").agg(F.count("*").alias("n"))
    graph = save(graph, "pii-graph")
    known = save(found.where("kind is not null").select("m", "kind").distinct(), "pii-known")
    shaped = save(graph.groupBy("context").agg(F.sum("n").alias("n_shaped")), "pii-shaped")
    # texts without a mention are searched only for contexts that pass in the others
    able_to_hold = F.rlike(F.coalesce("text", F.lit("")), F.lit("[0-9@]"))
    held, bare = docs.where(able_to_hold), docs.where(~able_to_hold)
    none = spark.range(0).select(F.lit("").alias("context"), F.col("id").alias("places"))
    in_held, in_bare, n_known = none, none, known.count()

    def counted(texts: DataFrame, contexts: DataFrame, told: DataFrame) -> DataFrame:
        """``told`` with the places of those ``contexts`` that it lacks; the texts do not change between rounds."""
        new = save(contexts.select("context").distinct().join(told, "context", "left_anti"), "pii-new")
        if new.isEmpty():
            return told
        places = new.join(marked_places(texts, new, most), "context", "left").select("context", F.coalesce("places", F.lit(0)).cast("long").alias("places"))
        return told.unionByName(save(places, "pii-places"))

    while True:
        by = graph.drop("kind").join(known, "m").groupBy("context", "kind").agg(F.count_distinct("m").alias("n_known"), F.sum("n").alias("known_places"))
        able = save(by.where(F.col("n_known") >= MIN_KNOWN).join(shaped, "context").where(F.col("known_places") >= MIN_PRECISION * F.col("n_shaped")), "pii-able")
        in_held = counted(held, able, in_held)
        able = save(able.join(in_held, "context").where(F.col("known_places") >= MIN_PRECISION * F.col("places")), "pii-able")
        in_bare = counted(bare, able, in_bare)
        scored = able.join(in_bare.withColumnRenamed("places", "more"), "context").withColumn("places", F.greatest(F.col("places") + F.col("more"), "n_shaped"))
        scored = scored.withColumn("precision", F.least(F.col("known_places") / F.col("places"), F.lit(0.99)))
        scored = save(scored.where(F.col("precision") >= MIN_PRECISION).select("context", F.col("kind").alias("as"), "precision"), "pii-patterns")
        # base entities keep their kind; a secret needs a pattern like any other identifier
        open_ = graph.where(F.col("kind").isNull() | (F.col("kind") == SECRET)).select("context", "m").distinct()
        belief = open_.join(scored, "context").groupBy("m", "as").agg((1 - F.exp(F.sum(F.log(1 - F.col("precision"))))).alias("belief"))
        accepted = save(belief.where(F.col("belief") >= MIN_BELIEF).groupBy("m").agg(F.max_by("as", F.struct("belief", "as")).alias("as")), "pii-accepted")
        known = save(known.unionByName(accepted.select("m", F.col("as").alias("kind"))).distinct(), "pii-known")
        before, n_known = n_known, known.count()
        if n_known == before:
            break
    return found.where(F.col("kind").isNull() | (F.col("kind") == SECRET)).join(accepted, "m").select("rid", F.col("as").alias("kind"), "s", "e")


def _listed(column: str) -> Column:
    return F.array_join(F.transform(column, lambda x: F.concat_ws(":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def extract(docs: DataFrame, **how) -> DataFrame:
    """(doc_id, base, spans): arrays of (kind, s, e) by kind, secrets last, then start; ends are exclusive.

    A null or empty text has no spans; repeated rows get a row each and a null
    id is passed on.  Base spans always stay; what the bootstrap adds touches
    none of them.  Other columns are not read.  An empty table gives no rows.
    """
    found = save(matches(docs), "pii-matches")
    spans = save(placed(found), "pii-spans")
    base = spans.where("kind <> 'loose'").select("rid", "kind", "s", "e", F.lit(True).alias("base"))
    added = discover(docs, save(mentions(spans), "pii-mentions"), **how).select("rid", "kind", "s", "e", F.lit(False).alias("base"))
    rank = F.array(*[F.lit(k) for k in (*KINDS, SECRET)])
    one = F.struct(F.array_position(rank, F.col("kind")).alias("k"), "s", "e", "kind", "base")
    by = base.unionByName(added).groupBy("rid").agg(F.array_sort(F.collect_list(one)).alias("x"))
    out = found.select("rid", "doc_id").join(by, "rid", "left")

    def bare(c: Column) -> Column:
        return F.coalesce(F.transform(c, lambda x: F.struct(x["kind"].alias("kind"), x["s"].alias("s"), x["e"].alias("e"))), F.array().cast("array<struct<kind:string,s:int,e:int>>"))

    return out.select("doc_id", bare(F.filter("x", lambda x: x["base"])).alias("base"), bare(F.col("x")).alias("spans"))


def redact(docs: DataFrame, spans: DataFrame) -> DataFrame:
    """(doc_id, text) with every span replaced by its kind in brackets; overlaps become one."""
    flat = spans.select(F.col("doc_id").alias("__id"), F.array_sort(F.transform("spans", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["kind"].alias("kind")))).alias("__spans"))
    joined = docs.join(flat, F.col("doc_id") == F.col("__id"), "left")
    zero = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        between = F.substring("text", acc["at"] + 1, F.greatest(F.lit(0), x["s"] - acc["at"]))
        mark = F.when(x["s"] >= acc["at"], F.concat(between, F.lit("["), x["kind"], F.lit("]"))).otherwise(F.lit(""))
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), F.concat(acc["out"], mark).alias("out"))

    done = F.aggregate("__spans", zero, step)
    text = F.when(F.col("__spans").isNull() | F.col("text").isNull(), F.col("text")).otherwise(F.concat(done["out"], F.substring("text", done["at"] + 1, F.length("text"))))
    return joined.select("doc_id", text.alias("text"))


def digest(docs: DataFrame) -> DataFrame:
    out = extract(docs)

    def count(kind: str) -> Column:
        return F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")

    return out.select("doc_id", *map(count, KINDS), F.sha2(_listed("base").cast("binary"), 256).alias("base_sha256"), _listed("spans").alias("spans"), F.size("spans").cast("long").alias("n_spans"))
