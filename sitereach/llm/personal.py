"""Personal data by bootstrapped contextual extraction, in DataFrame expressions only.

Base spans come from fixed patterns (e-mail, IPv4, card, phone). They seed the search, as do the values of
``SEEDS``: shapes of a kind beyond these four. What stands around a mention gives lexical patterns: the word
before it, the two words before it, and the words on both sides. The graph of patterns and
values is scored in rounds. A pattern's confidence for a kind is the score of the mentions that it surrounds
over all its occurrences in the corpus. A candidate is a word with digits (quotes around it left out) and the
digit groups joined to it by single separators, or a word like an e-mail address (``joe(at)site.org``), which
needs no digit. One that stands in a confident pattern, or repeats a value accepted elsewhere, is accepted as a
new mention with the confidence as its score, and feeds the next round; what is accepted stays, and the rounds
end when one accepts no new value. What is accepted in the end is added to the spans under the kind ``near_`` +
kind; base spans are never changed, and a candidate ends before one.

Positions are code points, end exclusive. A null or empty text has no span; a row keeps its own spans
whether or not its doc_id is null or repeated; an empty table gives an empty one; further columns are
not read by ``find`` and are kept by ``redacted``. Work grows in proportion to the length of a text: sums along
its matches are taken in windows or block by block, never from the start again.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import store

#: Kinds in order, and their patterns. Each is written so that the engine never looks at a
#: character more than a few times: a match starts where a run starts or where the last match ended.
KINDS = ("email", "ip", "card", "phone")
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Digit groups that carry on a word with digits, which must not end in a mark of punctuation.
GROUP = r"[(+]?[0-9][0-9()/.,;:+-]*+(?!\S)"
NAME, DOT, AT = r"[\p{L}\p{N}_%+-]++", r"(?:\.|\x20?[\[({<]dot[\])}>]\x20?|\x20dot\x20)", r"(?:@|\x20?[\[({<]at[\])}>]\x20?|\x20at\x20)"
#: Candidates, looked for behind every word (group 1) or at the head of the text: group 2 is the candidate, group 3 its first word, group 4 the word after it.
CANDIDATES = {
    "token": rf"[\"`]?+(?=(([^\s0-9\"`]*+[0-9][^\s\"`]*+)(?:(?<![,;:.!?])\x20(?:[/-]\x20)?{GROUP})*+)(?:\S*+\s++(\S++))?+)",
    "mail": rf"(?i)(?=(([^\s\p{{L}}\p{{N}}]*+{NAME}(?:{DOT}{NAME})*+(?:@{NAME}|{AT}{NAME}{DOT}{NAME})(?:{DOT}{NAME})*+))(?:\S*+\s++(\S++))?+)",
}
BEHIND = r"(?:(?<!\S)(\S++)|\A)\s++"
#: Whole candidates that are seeds of a further kind: keys and digests of 40 lower-case hexadecimal digits.
SEEDS = {"key": "^(?=.*[a-f])(?=.*[0-9])[0-9a-f]{40}$"}
#: Characters of a pattern that count.
CONTEXT = 80
#: A character that every match holds; texts without it are not searched.
NEEDS = {"email": "@", "phone": "+"}
#: Least confidence, least number of different values that a pattern has introduced.
CONFIDENCE, SUPPORT = 0.5, 3
#: Patterns, and characters of them, up to which they are sent to all tasks; beyond, words are counted first and then joined.
SENT_ROWS, SENT_CHARS = 500_000, 32 << 20
#: Elements of an array that one step of a running sum goes through.
BLOCK = 128


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        part = lambda x: F.regexp_replace(x, "^0+", "")
        return F.forall(F.split(value, r"\."), lambda x: (F.length(part(x)) < 3) | ((F.length(part(x)) == 3) & (part(x) <= "255")))
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "card":
        return F.length(digits).between(13, 19) & F.call_function("luhn_check", digits)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    if kind == "token":
        return F.length(digits) >= 4
    return F.lit(True)


def _bound(value: Column, use) -> Column:
    """``use(value)`` with the value worked out once, however often a lambda inside refers to it."""
    return F.element_at(F.transform(F.array(value), use), 1)


def running(values: Column, join) -> Column:
    """What ``join`` makes of 0 and all elements before each one (array<bigint>): block by block, so linear in the length."""
    start = F.struct(F.array().cast("array<bigint>").alias("seen"), F.lit(0).cast("bigint").alias("at"))
    step = lambda acc, v: F.struct(F.concat(acc["seen"], F.array(acc["at"])).alias("seen"), join(acc["at"], v).alias("at"))

    def whole(all_: Column) -> Column:
        firsts = F.sequence(F.lit(1), F.greatest(F.lit(1), F.size(all_)), F.lit(BLOCK))
        folded = F.transform(firsts, lambda i: F.aggregate(F.slice(all_, i, F.lit(BLOCK)), start, step))

        def joined(blocks: Column) -> Column:
            bases = F.aggregate(blocks, start, lambda acc, x: step(acc, x["at"]))["seen"]
            return F.flatten(F.transform(F.arrays_zip(blocks["seen"].alias("seen"), bases.alias("base")), lambda x: F.transform(x["seen"], lambda v: join(x["base"], v))))

        return _bound(folded, joined)

    return _bound(values, whole)


def _matches(kind: str, text: Column, context: bool = False) -> Column:
    """array<struct<kind, gap, size, tail, after, value>>: what stands between the matches, and the matches.

    ``tail`` (the end of the text before a match) and ``after`` (the next word) only with ``context``.
    """
    pattern = F.lit(PATTERNS[kind])
    parts, found = F.split(text, PATTERNS[kind], -1), F.regexp_extract_all(text, pattern, F.lit(0))
    zipped = _bound(F.struct(parts.alias("p"), found.alias("f")), lambda x: F.arrays_zip(F.slice(x["p"], 1, F.size(x["f"])).alias("gap"), x["f"].alias("value"), F.slice(x["p"], 2, F.size(x["f"])).alias("rest")))
    end = lambda x: F.substring(x, -CONTEXT, CONTEXT)

    def tail(all_: Column, x: Column, i: Column) -> Column:
        # a gap without two whole words is read on into the matches before it, of two characters at least each
        earlier = F.slice(all_, F.greatest(F.lit(1), i - CONTEXT // 2 + 1), F.least(i, F.lit(CONTEXT // 2)))
        longer = F.concat(F.array_join(F.transform(earlier, lambda y: F.concat(y["gap"], y["value"])), ""), x["gap"])
        return F.when((i == 0) | end(x["gap"]).rlike(r"\s\S+\s+\S+\s*$"), end(x["gap"])).otherwise(end(longer))

    after = lambda x: F.regexp_extract(F.substring(x["rest"], 1, CONTEXT), r"^\S*\s+(\S+)", 1)
    none = F.lit("")
    made = lambda all_: F.transform(all_, lambda x, i: F.struct(F.lit(kind).alias("kind"), F.length(x["gap"]).alias("gap"), F.length(x["value"]).alias("size"), (tail(all_, x, i) if context else none).alias("tail"), (after(x) if context else none).alias("after"), x["value"].alias("value")))
    rows = _bound(zipped, made)
    if kind in NEEDS:
        return F.when(F.instr(text, NEEDS[kind]) > 0, rows)
    return F.when(text.rlike("[0-9]"), rows)


def _candidates(kind: str, text: Column) -> Column:
    """array<struct<kind, gap, size, tail, after, value, word, head>>: what stands between the words before candidates, and these words and candidates.

    ``head`` is false where the candidate carries on a run of digit groups.
    """
    held, regex = F.concat(F.lit("\n"), text), BEHIND + CANDIDATES[kind]
    group = lambda i: F.regexp_extract_all(held, F.lit(regex), F.lit(i))
    listed = F.struct(F.split(held, regex, -1).alias("gap"), group(0).alias("all"), group(1).alias("before"), group(2).alias("value"), group(3).alias("word"), group(4).alias("after"))
    zipped = _bound(listed, lambda x: F.arrays_zip(F.slice(x["gap"], 1, F.size(x["all"])).alias("gap"), x["all"].alias("all"), x["before"].alias("before"), x["value"].alias("value"), x["word"].alias("word"), x["after"].alias("after")))
    runs_on = lambda x: F.endswith(x["all"], F.concat(x["before"], F.lit(" "))) & x["before"].rlike(f"^{GROUP}$") & ~x["before"].rlike("[,;:.!?]$") & x["word"].rlike(f"^{GROUP}$")
    # the word before the word before: at the end of the gap, or, in an empty gap, that of the last candidate
    lead = lambda all_, x, i: F.when((x["gap"] == "") & (i > 0), F.concat(F.get(all_, i - 1)["before"], F.lit(" "))).otherwise(F.right(x["gap"], F.lit(CONTEXT)))
    made = lambda all_: F.transform(all_, lambda x, i: F.struct(F.lit(kind).alias("kind"), F.length(x["gap"]).alias("gap"), F.length(x["all"]).alias("size"), F.concat(lead(all_, x, i), F.right(x["before"], F.lit(CONTEXT)), F.lit(" ")).alias("tail"), F.right(x["after"], F.lit(CONTEXT)).alias("after"), x["value"].alias("value"), x["word"].alias("word"), (~runs_on(x) if kind == "token" else F.lit(True)).alias("head")))
    return F.when(text.rlike("[0-9]" if kind == "token" else r"(?i)@|[\[({<]at[\])}>]|\x20at\x20"), _bound(zipped, made))


def _patterns(tail: Column, after: Column) -> Column:
    """The lexical patterns around a mention: word before, two words before, words on both sides."""
    one, two = (F.lower(F.regexp_extract(tail, rf"({w})\s*[\"`]?$", 1)) for w in (r"\S+", r"\S+\s+\S+"))
    one, two, next_ = F.right(one, F.lit(CONTEXT)), F.regexp_replace(two, r"\s+", " "), F.lower(after)
    return F.array_compact(F.array(*(F.when(ok, F.concat(F.lit(mark), *words)) for mark, ok, words in (("1 ", one != "", [one]), ("2 ", two != "", [two]), ("3 ", (one != "") & (next_ != ""), [one, F.lit(" "), next_])))))


def _occurrences(docs: DataFrame) -> DataFrame:
    """pattern: every place in the corpus where one could stand, whatever it surrounds."""
    listed = docs.select(F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "").alias("w")).where("size(w) > 0")
    rows = listed.select(F.inline(F.arrays_zip(F.col("w").alias("a"), F.slice("w", 2, F.size("w")).alias("b"), F.slice("w", 3, F.size("w")).alias("c"))))
    last = F.right("a", F.lit(CONTEXT))
    return rows.select(F.explode(F.array(F.concat(F.lit("1 "), last), F.concat(F.lit("2 "), "a", F.lit(" "), "b"), F.concat(F.lit("3 "), last, F.lit(" "), "c"))).alias("pattern")).where("pattern is not null")


def base_mentions(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(row, doc_id, hash of the text) of every row, and row, kind, start, end, patterns, value, word, head of every match and candidate, in any text."""
    rows = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("tag", F.xxhash64("text"))
    none = F.array().cast("array<struct<kind:string,gap:int,size:int,tail:string,after:string,value:string>>")
    no_candidate = F.array().cast("array<struct<kind:string,gap:int,size:int,tail:string,after:string,value:string,word:string,head:boolean>>")
    lists = [F.coalesce(_matches(k, F.col("text"), True), none).alias(k) for k in PATTERNS] + [F.coalesce(_candidates(k, F.col("text")), no_candidate).alias(k) for k in CANDIDATES]
    found = store.cut_and_free(rows.select("row", "doc_id", "tag", *lists), "matches")
    one = lambda kinds: found.select("row", F.explode(F.array(*kinds)).alias("list")).select("row", F.posexplode("list").alias("i", "m")).select("row", "i", "m.*")
    run = Window.partitionBy("row", "kind").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    to = F.sum(F.col("gap") + F.col("size")).over(run)
    placed = one(PATTERNS).withColumn("end", to).withColumn("start", F.col("end") - F.col("size"))
    ok = F.lit(False)
    for k in PATTERNS:
        ok = F.when(F.col("kind") == k, _valid(k, F.col("value"))).otherwise(ok)
    placed = placed.where(ok).select("row", "kind", "start", "end", _patterns(F.col("tail"), F.col("after")).alias("patterns"), "value", F.col("value").alias("word"), F.lit(True).alias("head"))
    # the text was read behind one added character, and a candidate begins where the match ends
    behind = one(CANDIDATES).withColumn("start", to - 1).withColumn("end", F.col("start") + F.length("value")).withColumn("patterns", _patterns(F.col("tail"), F.col("after")))
    return found.select("row", "doc_id", "tag"), placed.union(behind.select(*placed.columns))


def find(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(row, doc_id, hash of the text) of every row, and its spans: row, kind, start, end, value (added kinds start with ``near_``)."""
    rows, base, added = _found(docs)
    return rows, base.union(added)


def _apart(mentions: DataFrame) -> DataFrame:
    """The base mentions, and the candidates cut before the next base mention; candidates that begin in one go.

    A candidate of several words gives a row for its first word, too: that may repeat a known value.
    ``whole`` marks what counts if a pattern stands before it, ``follows`` what does stand behind one.
    """
    at = Window.partitionBy("row").orderBy("start", "end", "kind")
    base = ~F.col("kind").isin(*CANDIDATES)
    base_end = F.max(F.when(base, F.col("end"))).over(at.rowsBetween(Window.unboundedPreceding, -1))
    # read backwards: a frame that ends with the partition would be gone through again for each row
    back = Window.partitionBy("row").orderBy(F.desc("start"), F.desc("end"), F.desc("kind"))
    base_start = F.min(F.when(base, F.col("start"))).over(back.rowsBetween(Window.unboundedPreceding, -1))
    seen = mentions.withColumn("base_end", F.coalesce(base_end, F.lit(0))).withColumn("base_start", F.coalesce(base_start, F.col("end")))
    before_base = F.substring(F.col("value"), F.lit(1), (F.col("base_start") - F.col("start")).cast("int"))
    cut = F.when(F.col("base_start") >= F.col("end"), F.col("value")).when(before_base.rlike(r"\s"), F.regexp_replace(before_base, r"\s+\S*$", "")).otherwise("")
    rest = seen.where(~base & (F.col("base_end") <= F.col("start"))).withColumn("value", cut).where("value <> ''")
    forms = F.array(F.struct("value", F.col("head").alias("whole")), F.struct(F.col("word").alias("value"), F.lit(False).alias("whole")))
    one = rest.withColumn("form", F.explode(F.when(F.col("value") == F.col("word"), F.slice(forms, 1, 1)).otherwise(forms)))
    one = one.select("row", "kind", "start", (F.col("start") + F.length("form.value")).alias("end"), "patterns", "form.value", "form.whole", F.col("head").alias("follows"))
    one = one.where((F.col("kind") != "token") | _valid("token", F.col("value")))
    return seen.where(base).select("row", "kind", "start", "end", "patterns", "value", F.lit(True).alias("whole"), F.lit(True).alias("follows")).union(one)


def _found(docs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The rows, their base spans and the added ones."""
    rows, mentions = base_mentions(docs)
    mentions = store.cut_and_free(_apart(mentions), "mentions")
    base = ~F.col("kind").isin(*CANDIDATES)
    tokens = mentions.where(~base).withColumnRenamed("kind", "form")
    lone = F.coalesce(*(F.when(F.col("value").rlike(p), F.lit(k)) for k, p in SEEDS.items()))
    accepted = store.cut_and_free(tokens.select("value", lone.alias("kind"), F.lit(1.0).alias("score")).where("kind is not null").distinct(), "accepted")
    seeds = mentions.where(base).select("patterns", "kind", "value", F.lit(1.0).alias("score"))
    # a pattern of any round introduces values of the seeds or of candidates
    pattern = store.cut_and_free(mentions.where("follows").select("value", F.explode("patterns").alias("pattern")).groupBy("pattern").agg(F.countDistinct("value").alias("n")).where(F.col("n") >= SUPPORT).select("pattern"), "patterns")
    size = pattern.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.length("pattern")), F.lit(0)).alias("chars")).first()
    if size["n"] <= SENT_ROWS and size["chars"] <= SENT_CHARS:
        counted = _occurrences(docs).join(F.broadcast(pattern), "pattern").groupBy("pattern").agg(F.count("*").alias("total"))
    else:
        # patterns are unique, so an inner join keeps the same words; a semi join would be pushed below the count, and every word would then be shuffled uncounted
        counted = _occurrences(docs).groupBy("pattern").agg(F.count("*").alias("total")).join(pattern, "pattern")
    total = store.cut_and_free(counted, "patterns")
    while True:
        added = store.cut_and_free(tokens.join(accepted, "value"), "added")
        # a place counts once for its pattern, whether the run or its first word is known
        once = added.where("follows").groupBy("row", "start", "patterns", "kind").agg(F.max(F.struct("score", "value")).alias("best"))
        known = seeds.union(once.select("patterns", "kind", "best.value", "best.score")).withColumn("pattern", F.explode("patterns"))
        strength = known.groupBy("pattern", "kind").agg(F.sum("score").alias("hits"), F.countDistinct("value").alias("n")).where(F.col("n") >= SUPPORT)
        strong = strength.join(total, "pattern").select("pattern", "kind", (F.col("hits") / F.greatest("total", "hits")).alias("score")).where(F.col("score") >= CONFIDENCE)
        told = tokens.where("whole").withColumn("pattern", F.explode("patterns")).join(strong, "pattern").where("form <> 'mail' or kind = 'email'").select("value", "kind", "score")
        # one kind for each value, the likeliest; the value then counts wherever it stands, and is not judged again, so the rounds come to an end
        best = told.groupBy("value").agg(F.max(F.struct("score", "kind")).alias("best")).select("value", "best.kind", "best.score")
        new = store.cut_and_free(best.join(accepted.select("value"), "value", "left_anti"), "accepted")
        if new.isEmpty():
            break
        accepted = accepted.union(new)
    # a span within another one is left out
    earlier = F.max("end").over(Window.partitionBy("row").orderBy("start", F.desc("end"), F.desc("score"), "kind", "form").rowsBetween(Window.unboundedPreceding, -1))
    added = added.withColumn("earlier", earlier).where("earlier is null or earlier < end")
    spans = mentions.where(base).select("row", "kind", "start", "end", "value")
    return rows, spans, added.select("row", F.concat(F.lit("near_"), "kind").alias("kind"), "start", "end", "value")


_SPANS = "array<struct<start:bigint,end:bigint,kind:string>>"


def _good(kind: str, placed: Column) -> Column:
    good = F.filter(placed, lambda x: _valid(kind, x["value"]))
    return F.transform(good, lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), F.lit(kind).alias("kind")))


def base_spans(text: Column) -> Column:
    """The base spans of a text, within its row: array<struct<start, end, kind>>."""
    lists = []
    for kind in KINDS:

        def placed(found: Column) -> Column:
            before = running(F.transform(found, lambda m: (m["gap"] + m["size"]).cast("bigint")), lambda x, y: x + y)
            return F.transform(F.arrays_zip(found.alias("m"), before.alias("at")), lambda z: F.struct((z["at"] + z["m"]["gap"]).alias("start"), (z["at"] + z["m"]["gap"] + z["m"]["size"]).alias("end"), z["m"]["value"].alias("value")))

        lists.append(F.coalesce(_good(kind, _bound(_matches(kind, text), placed)), F.array().cast(_SPANS)))
    return F.concat(*lists)


def digest(docs: DataFrame) -> DataFrame:
    rows, spans = find(docs)
    order = F.coalesce(F.array_position(F.array(*map(F.lit, KINDS)), F.col("kind")), F.lit(0))
    place = F.when(order == 0, F.lit(len(KINDS) + 1)).otherwise(order)
    said = F.concat_ws(":", "kind", F.col("start").cast("string"), F.col("end").cast("string"))
    listed = spans.groupBy("row").agg(F.sort_array(F.collect_list(F.struct(place.alias("at"), "kind", "start", "end", said.alias("said")))).alias("all"), *(F.sum((F.col("kind") == k).cast("long")).alias(f"n_{k}") for k in KINDS))
    joined = lambda x: F.array_join(F.transform(x, lambda s: s["said"]), ",")
    out = rows.join(listed, "row", "left").withColumn("all", F.coalesce("all", F.array().cast("array<struct<at:bigint,kind:string,start:bigint,end:bigint,said:string>>")))
    base = F.filter("all", lambda s: s["at"] <= len(KINDS))
    return out.select("doc_id", *(F.coalesce(f"n_{k}", F.lit(0)).cast("long").alias(f"n_{k}") for k in KINDS), F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("all")).alias("spans"), F.size("all").cast("long").alias("n_spans"), (F.size("all") - F.size(base)).cast("long").alias("n_added"))


def redacted(docs: DataFrame) -> DataFrame:
    """The rows with every span replaced by its kind in angle brackets, and ``n_chars``, if there is one, counted again.

    Overlapping spans are replaced once, under the kind of the first. The text is cut in a fixed-width
    encoding, so a long text with many spans costs no more than its length.
    """
    rows, _, added = _found(docs)
    local = base_spans(F.coalesce(docs["text"], F.lit("")))
    if added.isEmpty():
        out = docs.withColumn("__spans", F.array_sort(local))
    else:
        # only rows with added spans have something to be joined
        listed = rows.join(added, "row").select("doc_id", "tag", F.struct(F.col("start").cast("bigint").alias("start"), F.col("end").cast("bigint").alias("end"), "kind").alias("s")).distinct().groupBy(F.col("doc_id").alias("__id"), F.col("tag").alias("__tag")).agg(F.collect_list("s").alias("__added"))
        out = docs.join(listed, docs["doc_id"].eqNullSafe(F.col("__id")) & (F.xxhash64(F.coalesce(docs["text"], F.lit(""))) == F.col("__tag")), "left")
        out = out.withColumn("__spans", F.array_sort(F.concat(local, F.coalesce(F.col("__added"), F.array().cast(_SPANS)))))
    lead = F.encode(F.lit("x"), "UTF-32")  # keeps a byte order mark at the head of a piece from being dropped
    piece = lambda wide, at, to: F.substring(F.decode(F.concat(lead, F.substring(wide, at * 4 + 1, (to - at) * 4)), "UTF-32"), 2, 2147483647)

    def cut(x: Column) -> Column:
        before = running(F.transform(x["spans"], lambda s: s["end"].cast("bigint")), F.greatest)
        cuts = F.filter(F.arrays_zip(before.alias("at"), x["spans"].alias("s")), lambda c: c["s"]["start"] >= c["at"])
        shown = F.transform(cuts, lambda c: F.concat(piece(x["wide"], c["at"], c["s"]["start"]), F.lit("<"), c["s"]["kind"], F.lit(">")))
        return F.concat(F.array_join(shown, ""), piece(x["wide"], F.array_max(F.transform(x["spans"], lambda s: s["end"])), x["n"]))

    some = F.size("__spans") > 0
    out = out.withColumn("__cut", F.when(some, _bound(F.struct(F.encode(docs["text"], "UTF-32").alias("wide"), F.col("__spans").alias("spans"), F.length(docs["text"]).cast("bigint").alias("n")), cut)))
    new = F.coalesce("__cut", docs["text"])
    return out.select(*(new.alias("text") if c == "text" else F.when(F.col("__cut").isNull(), docs["n_chars"]).otherwise(F.length(new)).cast(docs.schema["n_chars"].dataType).alias("n_chars") if c == "n_chars" else docs[c] for c in docs.columns))


def op7_personal_data(spark, sf_dir: str) -> DataFrame:
    return digest(spark.read.parquet(f"{sf_dir}/documents.parquet"))
