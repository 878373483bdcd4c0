"""From paths to scoped samples: pairs, statements, questions and answers, guards, audits, export."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import u01, words
from ..functions.session import cut, small
from ..sources.carriers import records_of
from .cooccurrence import best_of_many


def path_pairs(paths: DataFrame) -> DataFrame:
    """Adjacent nodes of each path in order: target, role, walk_id, pos, left, right, w, origin (the path's first node)."""
    rows = paths.select("target", "role", "walk_id", "nodes", F.element_at("nodes", 1).alias("origin"), F.posexplode("weights").alias("pos", "w"))
    return rows.select("target", "role", "walk_id", "pos", F.get("nodes", F.col("pos")).alias("left"), F.get("nodes", F.col("pos") + 1).alias("right"), "w", "origin")


def event_statements(pairs: DataFrame, mentions: DataFrame, texts: DataFrame | None = None) -> DataFrame:
    """One statement for each distinct (target, left, right): the shortest record that mentions both, of those that also mention
    the target if there are any; ties by id. Carriers without texts get a template. Pairs are few (walks bound them)."""
    distinct = cut(pairs.select("target", "left", "right").distinct())
    aim = cut(met_with(mentions, distinct.select("target").distinct().withColumnRenamed("target", "cue")).withColumnsRenamed({"cue": "target"}))

    def least(both: DataFrame) -> DataFrame:
        if texts is not None:
            both = both.join(texts.select("record_id", "text"), "record_id")
            size, text = F.length("text"), F.col("text")
        else:
            size, text = F.length("record_id"), F.concat_ws(" ", "left", F.lit("goes with"), "right")
        return cut(both.groupBy("target", "left", "right").agg(F.min(F.struct(size.alias("n"), F.col("record_id"), text.alias("statement"))).alias("b")))

    # records of the target come first, so all others are gone through only for the pairs that none of them mentions
    best = least(small(distinct).join(aim.withColumnRenamed("entity", "left"), ["target", "left"]).join(aim.withColumnRenamed("entity", "right"), ["target", "right", "record_id"]))
    rest = cut(distinct.join(best, ["target", "left", "right"], "left_anti"))
    if not rest.isEmpty():
        records = records_of(mentions)
        if records is not None:
            lefts = records.select("record_id", "facts", F.explode("facts").alias("left")).join(small(rest), "left")
            both = lefts.filter(F.array_contains("facts", F.col("right"))).select("target", "left", "right", "record_id")
        else:
            both = mentions.withColumnRenamed("entity", "left").join(small(rest), "left").join(mentions.withColumnRenamed("entity", "right"), ["right", "record_id"])
        best = best.unionByName(least(both))
    made = F.concat_ws(" ", "left", F.lit("goes with"), "right")
    return distinct.join(best, ["target", "left", "right"], "left").select("target", "left", "right", F.col("b.record_id").alias("evidence_id"), F.coalesce("b.statement", made).alias("statement"))


def _question(style: str, answer, first, second):
    asks = {
        "qa": F.concat_ws("", F.lit("Which entity is tied to "), first, F.when(second.isNotNull() & (second != first) & (second != answer), F.concat(F.lit(" and "), second)).otherwise(""), F.lit("?")),
        "cloze": F.concat_ws(" ", F.lit("____ goes with"), first),
        "statement": F.concat_ws(" ", first, F.lit("belongs to the story of")),
    }
    return asks[style]


def _samples(rows: DataFrame, role: str, generator: str, style: str) -> DataFrame:
    """rows: target, walk_id, pos, obj, cue2, answer, evidence_id -> samples with the answer's character span in `question answer`."""
    question = _question(style, F.col("answer"), F.col("obj"), F.col("cue2"))
    rows = rows.withColumn("question", question)
    start = F.length("question") + 1
    key = F.concat_ws("|", "target", F.lit(role), F.lit(generator), "walk_id", "pos", "obj", "answer")
    return rows.select(F.md5(key).alias("sample_id"), "target", F.lit(role).alias("role"), F.lit(generator).alias("generator"), "question", "obj", "cue2", "answer", F.struct(start.alias("start"), (start + F.length("answer")).alias("end")).alias("span"), "walk_id", "pos", "evidence_id")


def forget_samples(pairs: DataFrame, statements: DataFrame, *, obj_rule: str = "non_target", style: str = "qa", generator: str = "graph_recall") -> DataFrame:
    """The left node is the cue and the target the answer; where the left node is the target, `non_target` asks by the right one."""
    leaks = (F.col("left") == F.col("target")) if obj_rule == "non_target" else F.lit(False)
    rows = pairs.filter("role = 'forget'").join(statements, ["target", "left", "right"])
    rows = rows.select("target", "walk_id", "pos", F.when(leaks, F.col("right")).otherwise(F.col("left")).alias("obj"), F.when(leaks, None).otherwise(F.col("right")).alias("cue2"), F.col("target").alias("answer"), "evidence_id")
    return _samples(rows, "forget", generator, style)


def neighbor_samples(pairs: DataFrame, statements: DataFrame, *, answer: str = "start", style: str = "qa", generator: str = "graph_recall") -> DataFrame:
    """The answer is a neighbour (the path's start, or each pair's left node); the target must not be in the question."""
    a = F.col("origin") if answer == "start" else F.col("left")
    rows = pairs.filter("role = 'neighbor'").join(statements, ["target", "left", "right"]).withColumn("answer", a)
    rows = rows.withColumn("obj", F.when(F.col("left") == F.col("answer"), F.col("right")).otherwise(F.col("left"))).withColumn("cue2", F.when(F.col("left") == F.col("answer"), None).otherwise(F.col("right")))
    rows = rows.filter((F.col("obj") != F.col("target")) & (F.coalesce("cue2", F.lit("")) != F.col("target")) & (F.col("obj") != F.col("answer")))
    return _samples(rows.select("target", "walk_id", "pos", "obj", "cue2", "answer", "evidence_id"), "neighbor", generator, style)


def retain_samples(mentions: DataFrame, nodes: DataFrame, m: int, seed: int = 42) -> DataFrame:
    """m records for each target that mention none of its graph's nodes, in a keyed order of records: target, record_id, at.

    Only the first records of that order are looked at, sixteen times as many each time until all targets have theirs; never all records by all targets.
    """
    records = cut(mentions.select("record_id").distinct())
    targets = cut(nodes.select("target").distinct())
    total, take = records.count(), 4 * m
    while True:
        first = cut(records.orderBy(u01(seed, "record_id"), "record_id").limit(take))
        held = mentions.join(F.broadcast(first), "record_id", "left_semi")
        touched = held.join(nodes.select("target", "entity").distinct(), "entity").select("target", "record_id").distinct()
        free = targets.crossJoin(F.broadcast(first)).join(touched, ["target", "record_id"], "left_anti")  # targets by `take` rows
        at = F.row_number().over(Window.partitionBy("target").orderBy(u01(seed, "record_id"), "record_id"))
        found = cut(free.withColumn("at", at).filter(F.col("at") <= m))
        short = targets.join(found.groupBy("target").agg(F.count("*").alias("n")), "target", "left").filter(F.coalesce("n", F.lit(0)) < m)
        if take >= total or short.isEmpty():
            return found
        take *= 16


def answer_mask(samples: DataFrame) -> DataFrame:
    """loss_mask: 1 for the words of `question answer` that belong to the answer, 0 before."""
    count = lambda c: F.size(F.split(c, " "))
    return samples.withColumn("loss_mask", F.concat(F.array_repeat(F.lit(0), count("question")), F.array_repeat(F.lit(1), count("answer"))))


def validate_samples(samples: DataFrame) -> DataFrame:
    """Adds reason: leak (answer in the question), ambiguous (its cues point to several answers) or ok."""
    cues = samples.groupBy("role", "obj", "cue2").agg(F.countDistinct("answer").alias("answers")).select(F.col("role").alias("_r"), F.col("obj").alias("_o"), F.col("cue2").alias("_c"), "answers")
    rows = samples.join(cues, (F.col("role") == F.col("_r")) & (F.col("obj") == F.col("_o")) & F.col("cue2").eqNullSafe(F.col("_c"))).drop("_r", "_o", "_c")
    return rows.withColumn("reason", F.when(F.instr("question", F.col("answer")) > 0, "leak").when(F.col("answers") > 1, "ambiguous").otherwise("ok")).drop("answers")


def scope_report(samples: DataFrame) -> DataFrame:
    """By target: answers on the forget side, on the neighbour side, on both (must be 0), and cues that both sides use."""
    a = samples.groupBy("target").agg(
        F.count_distinct(F.when(F.col("role") == "forget", F.col("answer"))).alias("forget_answers"), F.count_distinct(F.when(F.col("role") == "neighbor", F.col("answer"))).alias("neighbor_answers")
    )
    both = lambda c, name: samples.groupBy("target", c).agg(F.count_distinct("role").alias("k")).filter("k > 1").groupBy("target").agg(F.count("*").alias(name))
    rows = a.join(both("answer", "shared_answers"), "target", "left").join(both("obj", "boundary_cues"), "target", "left")
    return rows.na.fill(0, ["shared_answers", "boundary_cues"])


def samples_json(samples: DataFrame, seed: int = 42) -> DataFrame:
    """Fine-tuning lines in keyed order: at, line."""
    line = F.to_json(F.struct("question", "answer", "role"))
    at = F.row_number().over(Window.partitionBy("target").orderBy(u01(seed, "sample_id"), "sample_id"))
    return samples.select("target", "sample_id", at.alias("at"), line.alias("line"))


def export_samples(samples: DataFrame, path: str, fmt: str = "json") -> None:
    """Answer spans and masks go along, so a trainer can count the answer only."""
    answer_mask(samples).write.mode("overwrite").partitionBy("role").format(fmt).save(path)


def audit_trail(samples: DataFrame, edges: DataFrame, responses: DataFrame, mentions: DataFrame) -> DataFrame:
    """sample_id -> edge from its cue's anchor -> first response that produced it, which is the first one whose record mentions the edge's node."""
    e = edges.filter("kept").select("target", "src", "dst", "c")
    rows = samples.select("sample_id", "target", "obj").join(e, (samples["target"] == e["target"]) & (samples["obj"] == e["dst"])).select("sample_id", e["target"], "src", "dst", "c")
    asked = rows.select("target", "src", "dst").distinct().join(responses.select("target", F.col("anchor").alias("src"), "iter", "record_id"), ["target", "src"])
    first = asked.join(mentions.withColumnRenamed("entity", "dst"), ["record_id", "dst"]).groupBy("target", "src", "dst").agg(F.min_by("record_id", "iter").alias("response_id"))
    return rows.join(first, ["target", "src", "dst"], "left").select("sample_id", "target", "src", "dst", "c", "response_id")


def windows(texts: DataFrame, lengths: list[int] | None, width: int = 10) -> DataFrame:
    """texts (text, ...) -> with n, gram: every run of `width` words (all words of a shorter text), or of each of the given numbers of words."""
    rows = texts.withColumn("_w", words(F.col("text"))).filter(F.size("_w") > 0)
    sizes = F.array(F.least(F.lit(width), F.size("_w"))) if lengths is None else F.array(*[F.lit(n) for n in lengths]).cast("array<int>")
    rows = rows.withColumn("n", F.explode(sizes)).filter(F.size("_w") >= F.col("n"))
    at = F.sequence(F.lit(1), F.size("_w") - F.col("n") + 1)
    return rows.withColumn("gram", F.explode(F.transform(at, lambda i: F.array_join(F.slice("_w", i, F.col("n")), " ")))).drop("_w")


def audit_forget_set(samples: DataFrame, planted: DataFrame, *, text: str = "text", target: str = "target") -> DataFrame:
    """An externally supplied forget set (target, text): off-topic share, exact copies, texts that hold ten words in a row of a planted passage (or a shorter one whole), personal data, by target."""
    rows = samples.select(F.col(target).alias("target"), F.col(text).alias("text"))
    rows = rows.withColumn("off", ~F.contains(F.lower("text"), F.lower("target"))).withColumn("mail", F.col("text").rlike("[a-zA-Z0-9._]+@[a-zA-Z0-9.]+")).withColumn("digits", F.col("text").rlike("[0-9]{7,}"))
    passages = windows(planted.select("text"), None).select("n", "gram").distinct()
    lengths = [r["n"] for r in passages.select("n").distinct().collect()]  # ten at most
    grams = windows(rows.select("target", "text").distinct(), lengths)
    hit = grams.join(small(passages), ["n", "gram"], "left_semi").select("target", "text").distinct().withColumn("planted", F.lit(1))
    rows = rows.join(hit, ["target", "text"], "left")
    return rows.groupBy("target").agg(
        F.count("*").alias("n"), F.sum(F.col("off").cast("long")).alias("off_topic"), (F.count("*") - F.count_distinct("text")).alias("copies"),
        F.sum(F.coalesce("planted", F.lit(0)).cast("long")).alias("planted"), F.sum((F.col("mail") | F.col("digits")).cast("long")).alias("personal"),
    )


def request_exposure(texts: DataFrame) -> DataFrame:
    """Characters and personal data handed over with whole texts (target, text) against the anchor alone."""
    hits = F.size(F.regexp_extract_all("text", F.lit("[a-zA-Z0-9._]+@[a-zA-Z0-9.]+|[0-9]{7,}"), F.lit(0)))
    return texts.groupBy("target").agg(F.sum(F.length("text")).alias("chars_texts"), F.length("target").alias("chars_anchor"), F.sum(hits).cast("long").alias("personal_hits"))


def cooccur(mentions: DataFrame, cues: DataFrame) -> DataFrame:
    """cues (cue) -> cue, ans, c: records of the pool that mention both."""
    return met_with(mentions, cues).filter("entity <> cue").groupBy("cue", F.col("entity").alias("ans")).agg(F.count("*").alias("c"))


def met_with(mentions: DataFrame, cues: DataFrame) -> DataFrame:
    """cues (cue, distinct) -> cue, record_id, entity: all mentions of the records that mention a cue. A pool of records is gone through once, without a shuffle."""
    cues, records = small(cut(cues)), records_of(mentions)
    if records is not None:
        return records.select("record_id", "facts", F.explode("facts").alias("cue")).join(cues, "cue").select("cue", "record_id", F.explode("facts").alias("entity"))
    return mentions.withColumnRenamed("entity", "cue").join(cues, "cue").select("cue", "record_id").join(mentions, "record_id").select("cue", "record_id", "entity")


#: Entities of a pool, the most frequent ones, whose counts with every cue are taken first.
HEAVY = 1000
#: Cues beyond which all pairs of a pool of records are counted by blocks of cues.
MANY = 2000


def best_answers(mentions: DataFrame, cues: DataFrame, support: int, named: DataFrame, less: DataFrame | None = None, heavy: int = HEAVY) -> DataFrame:
    """cues (target, cue) -> target, cue, ans, c: counts as of `cooccur`, exact, of the target, of the `support` most frequent answers (ties by name) and of the answers
    `named` (ans) at least; a row with null ans holds the sum of all answers of the cue.

    less: target, cue, ans, c to be taken off (records left out).

    A count is at most the answer's own number of records. So if the least of a cue's `support` best counts with frequent entities is above the records of the most frequent
    entity beyond those, no other answer can be among the best; a cue where it isn't, a rare one, is counted with all entities. Rare answers of frequent cues, nearly all
    pairs of a pool, are thus never counted one by one. Many cues are mostly rare ones: then all pairs are counted, by blocks of cues (`cooccurrence`).
    """
    cues = cut(cues.distinct())
    if less is None and records_of(mentions) is not None:
        asked = cut(cues.select("cue").distinct())
        if asked.count() > MANY and (found := best_of_many(records_of(mentions), asked, support, named.select("ans").union(cues.select("target")))) is not None:
            best, sums = found
            sums = sums.select("cue", F.lit(None).cast("string").alias("ans"), "c").filter("c > 0")
            return cues.join(best.unionByName(sums), "cue").select("target", "cue", "ans", "c")
    sizes = mentions.groupBy("entity").agg(F.count("*").alias("df"))
    first = cut(sizes.orderBy(F.desc("df"), "entity").limit(heavy + 1))
    beyond = first.orderBy("df", F.desc("entity")).limit(1).select(F.when(F.lit(first.count() > heavy), F.col("df")).otherwise(0).alias("beyond"))
    some = cut(first.orderBy(F.desc("df"), "entity").limit(heavy).select("entity").union(named.select("ans")).union(cues.select("target")).distinct())
    met = met_with(mentions, cues.select("cue").distinct()).filter("entity <> cue")
    ans = F.col("_found")  # null for all answers beyond the chosen ones: their sum
    counted = met.join(small(some.select("entity", F.col("entity").alias("_found"))), "entity", "left").groupBy("cue", ans.alias("ans")).agg(F.count("*").alias("c"))
    counted = cut(counted)

    def minus(rows: DataFrame) -> DataFrame:
        if less is None:
            return rows
        return rows.join(less.withColumnRenamed("c", "_less"), ["target", "cue", "ans"], "left").withColumn("c", F.col("c") - F.coalesce("_less", F.lit(0))).drop("_less").filter("c > 0")

    own = cut(minus(cues.join(counted.filter("ans is not null"), "cue").select("target", "cue", "ans", "c")))
    at = F.row_number().over(Window.partitionBy("target", "cue").orderBy((F.col("ans") == F.col("target")).desc(), F.desc("c"), "ans"))
    last = own.withColumn("at", at).filter(F.col("at") == support).crossJoin(F.broadcast(beyond)).filter("c > beyond or beyond = 0").select("target", "cue")
    few = counted.groupBy("cue").agg(F.max(F.col("ans").isNull()).alias("more")).filter("not more").select("cue")  # all answers are among the chosen ones
    settled = cut(last.unionByName(cues.join(few, "cue").select("target", "cue")).distinct())
    rest = cut(cues.join(settled, ["target", "cue"], "left_anti"))
    rare = minus(cooccur(mentions, rest.select("cue").distinct()).join(rest, "cue").select("target", "cue", "ans", "c"))
    total = cues.join(counted.groupBy("cue").agg(F.sum("c").alias("c")), "cue").select("target", "cue", F.lit(None).cast("string").alias("ans"), "c")
    if less is not None:
        off = less.groupBy("target", "cue").agg(F.sum("c").alias("_less"))
        total = total.join(off, ["target", "cue"], "left").withColumn("c", F.col("c") - F.coalesce("_less", F.lit(0))).drop("_less")
    return own.join(settled, ["target", "cue"], "left_semi").unionByName(rare).unionByName(total)
