"""Responders: what a model answers when asked about an anchor in the context of a target.

All give responses(target, anchor, hop, iter, response_id, text) and, for pools, mentions by record.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import u01
from ..functions.session import cut, small
from .carriers import records_of


class PoolResponder:
    """A table of records in the place of a model: response i is the i-th record of a keyed order of those that mention the anchor.

    The frontier of an expansion is bounded by budget times targets, so it is broadcast when its size allows; postings are then
    filtered at the scan and only the n best records of each anchor go on (a top-n window that Spark limits before the shuffle).
    """

    def __init__(self, mentions: DataFrame, *, n: int = 20, seed: int = 42, conditioning: str = "soft", replace: bool = False, short_pool: str = "empty", keep_return: bool = False, terms: DataFrame | None = None):
        """terms: target, entity: what an anchor sentence says of the target; records that mention more of it come first. keep_return: mentions of the target count too."""
        self.mentions, self.n, self.seed, self.conditioning, self.replace, self.short_pool = mentions, n, seed, conditioning, replace, short_pool
        self.keep_return, self.terms = keep_return, terms
        self._others_held: list[DataFrame] = []  # record_id, facts: records that `_others` found

    def evidence(self) -> tuple[DataFrame, DataFrame | None]:
        """Mentions by record, and texts by record if there are any, as proof of what was recalled."""
        return self.mentions, None

    def of_target(self, frontier: DataFrame) -> DataFrame:
        """target, record_id, entity: all mentions of the records that mention a target of the frontier; kept with the pool for later hops and responders, which ask for the same ones."""
        from ..operators.supervision import met_with

        asked, held = cut(frontier.select("target").distinct()), getattr(self.mentions, "_aim", None)
        if held is None or not asked.join(held[0], "target", "left_anti").isEmpty():
            held = asked, cut(met_with(self.mentions, asked.withColumnRenamed("target", "cue")).withColumnRenamed("cue", "target"))
            self.mentions._aim = held
        return held[1]

    def candidates(self, frontier: DataFrame) -> DataFrame:
        """target, anchor, hop, record_id, has_target, n_terms: of anchors with more records those at least that can be among the first n."""
        frontier = cut(frontier)
        aim = self.of_target(frontier)
        close = cut(aim.withColumnRenamed("entity", "anchor").join(small(frontier), ["target", "anchor"]).select("target", "anchor", "hop", "record_id"))
        near = close.withColumn("has_target", F.lit(True))
        if self.conditioning == "strict":
            found = near
        elif self.conditioning == "soft" and self.terms is None and not self.replace:
            # records of the target come before all others, so other records count only for anchors that have fewer than n of them
            met = close.groupBy("target", "anchor").agg(F.count("*").alias("met"))
            rest = cut(frontier.join(met, ["target", "anchor"], "left").filter(F.coalesce("met", F.lit(0)) < self.n).select("target", "anchor", "hop"))
            found = near if rest.isEmpty() else near.unionByName(self._others(rest, close))
        else:
            of = small(cut(aim.filter("entity = target").select("target", "record_id"))).withColumn("has_target", F.lit(True))
            postings = self.mentions.withColumnRenamed("entity", "anchor").join(small(frontier), "anchor").select("target", "anchor", "hop", "record_id")
            found = postings.join(of, ["target", "record_id"], "left").withColumn("has_target", F.coalesce("has_target", F.lit(False)))
        if self.terms is None:
            return found.withColumn("n_terms", F.lit(0).cast("long"))
        said = self.mentions.join(small(self.terms.select("target", "entity").distinct()), "entity").groupBy("target", "record_id").agg(F.count("*").alias("n_terms"))
        return found.join(said, ["target", "record_id"], "left").na.fill(0, ["n_terms"])

    def _others(self, rest: DataFrame, close: DataFrame) -> DataFrame:
        """Records of anchors that don't mention the target, with the first n in order of draws among them.

        Of an anchor with many records only draws below a bound are kept, which some 3 n + 30 are; an anchor that is left with too few is asked again without a bound.
        """
        postings = self.mentions.withColumnRenamed("entity", "anchor")
        rest = cut(rest.join(postings.join(small(rest.select("anchor").distinct()), "anchor").groupBy("anchor").agg(F.count("*").alias("of")), "anchor"))
        draw = u01(self.seed, "target", "anchor", "record_id")
        records = records_of(self.mentions)
        rows = postings if records is None else records.select("record_id", "facts", F.explode("facts").alias("anchor"))
        keep = lambda asks, where: rows.join(small(asks), "anchor").filter(where).join(small(close.select("target", "anchor", "record_id")), ["target", "anchor", "record_id"], "left_anti")
        some = cut(keep(rest, draw * F.col("of") < 3 * self.n + 30))
        if records is not None:
            self._others_held.append(some.select("record_id", "facts"))
        some = some.select("target", "anchor", "hop", "record_id")
        got = some.groupBy("target", "anchor").agg(F.count("*").alias("got")).unionByName(close.groupBy("target", "anchor").agg(F.count("*").alias("got")))
        got = got.groupBy("target", "anchor").agg(F.sum("got").alias("got"))
        short = cut(rest.join(got, ["target", "anchor"], "left").filter(F.coalesce("got", F.lit(0)) < F.least(F.lit(self.n), F.col("of"))).select("target", "anchor", "hop", "of"))
        if not short.isEmpty():
            some = some.join(small(short.select("target", "anchor")), ["target", "anchor"], "left_anti").unionByName(keep(short, F.lit(True)).select("target", "anchor", "hop", "record_id"))
        return some.withColumn("has_target", F.lit(False))

    def respond(self, frontier: DataFrame) -> DataFrame:
        """frontier (target, anchor, hop) -> target, anchor, hop, iter, record_id."""
        rows = self.candidates(frontier)
        draw = u01(self.seed, "target", "anchor", "record_id")
        if self.replace:
            by = Window.partitionBy("target", "anchor")
            ranked = rows.withColumn("at", F.row_number().over(by.orderBy("record_id"))).withColumn("of", F.count("*").over(by))
            asks = frontier.select("target", "anchor", F.explode(F.sequence(F.lit(1), F.lit(self.n))).alias("iter"))
            sizes = ranked.groupBy("target", "anchor").agg(F.max("of").alias("of"))
            asks = asks.join(sizes, ["target", "anchor"]).withColumn("at", (1 + F.floor(u01(self.seed, "target", "anchor", "iter") * F.col("of"))).cast("int"))
            return asks.drop("of").join(ranked.drop("of"), ["target", "anchor", "at"]).select("target", "anchor", "hop", "iter", "record_id")
        order = [draw, F.col("record_id")] if self.conditioning == "none" else [F.desc("has_target"), F.desc("n_terms"), draw, F.col("record_id")]
        ranked = rows.withColumn("iter", F.row_number().over(Window.partitionBy("target", "anchor").orderBy(*order)))
        return ranked.filter(F.col("iter") <= self.n).select("target", "anchor", "hop", "iter", "record_id")

    def denominators(self, responses: DataFrame) -> DataFrame:
        """target, anchor, n_resp: a short pool's missing responses are empty ones, or with `shrink` not asked for."""
        asked = responses.groupBy("target", "anchor").agg(F.count("*").alias("n_resp"))
        return asked if self.short_pool == "shrink" else asked.withColumn("n_resp", F.lit(self.n).cast("long"))

    def extract(self, responses: DataFrame) -> DataFrame:
        """Entities of the responses but anchor and target: target, anchor, hop, iter, entity."""
        asked, records = small(cut(responses)), records_of(self.mentions)  # n for each anchor
        if records is not None:
            aim = getattr(self.mentions, "_aim", None)
            held = [aim[1].select("record_id", "entity")] if aim else []
            held += [x.select("record_id", F.explode("facts").alias("entity")) for x in self._others_held]
            known = reduce(DataFrame.union, held).distinct() if held else None
            if known is not None and asked.select("record_id").distinct().join(known.select("record_id").distinct(), "record_id", "left_anti").isEmpty():
                rows = known.join(asked, "record_id")  # all of them were met when they were chosen
            else:
                rows = records.join(asked, "record_id").withColumn("entity", F.explode("facts")).drop("facts")
        else:
            rows = self.mentions.join(asked, "record_id")
        return _but_itself(rows, self.keep_return)

    def padded(self, responses: DataFrame) -> DataFrame:
        """All n iterations of each anchor, those beyond a short pool with a null record."""
        asks = responses.select("target", "anchor", "hop").distinct().withColumn("iter", F.explode(F.sequence(F.lit(1), F.lit(self.n))))
        return asks.join(responses, ["target", "anchor", "hop", "iter"], "left").select("target", "anchor", "hop", "iter", "record_id")


def _but_itself(rows: DataFrame, keep_return: bool) -> DataFrame:
    """Mentions of anything but the anchor and, unless return edges are kept, the target."""
    free = F.col("entity") != F.col("anchor")
    return rows.filter(free if keep_return else free & (F.col("entity") != F.col("target"))).select("target", "anchor", "hop", "iter", "entity")


class TextResponder:
    """Answers as texts, by a function from a frontier to responses (target, anchor, hop, iter, response_id, text): a live model (`model_responder`) or recorded answers.

    extract: responses -> keys and entity, such as a lexicon or a user's extractor. Every answer is written before it is used, and kept as evidence.
    """

    short_pool = "empty"

    def __init__(self, answer: Callable[[DataFrame], DataFrame], extract: Callable[[DataFrame], DataFrame], *, n: int = 20, keep_return: bool = False):
        self.answer, self._extract, self.n, self.keep_return = answer, extract, n, keep_return
        self.asked: list[DataFrame] = []

    def respond(self, frontier: DataFrame) -> DataFrame:
        got = cut(self.answer(frontier).filter(F.col("iter") <= self.n).select("target", "anchor", F.col("hop").cast("int").alias("hop"), F.col("iter").cast("int").alias("iter"), F.col("response_id").alias("record_id"), "text"))
        self.asked.append(got)
        return got

    def extract(self, responses: DataFrame) -> DataFrame:
        return _but_itself(self._extract(responses).select("target", "anchor", "hop", "iter", "entity").distinct(), self.keep_return)

    def evidence(self) -> tuple[DataFrame, DataFrame]:
        """Of each answer what it mentions, its anchor and target included, and its text."""
        rows = self.asked[0]
        for more in self.asked[1:]:
            rows = rows.unionByName(more)
        named = self._extract(rows).select("record_id", "entity").unionByName(rows.filter("text is not null").select("record_id", F.explode(F.array("target", "anchor")).alias("entity")))
        return cut(named.distinct()), rows.filter("text is not null").select("record_id", "text")


def model_responder(call: Callable[[list[str]], list[str | None]], lexicon: DataFrame, *, n: int = 20, **options) -> TextResponder:
    """A live model behind `call`, which answers a batch of prompts; mentions by a lexicon (entity)."""
    from ..operators.entities import extract_mentions

    def answer(frontier: DataFrame) -> DataFrame:
        asks = frontier.select("target", "anchor", "hop", F.explode(F.sequence(F.lit(1), F.lit(n))).alias("iter"))
        return call_model(render_prompts(asks), call, **options)

    return TextResponder(answer, lambda r: extract_mentions(r, lexicon, keys=["target", "anchor", "hop", "iter", "record_id"]), n=n)


def recorded_responder(answers: DataFrame, lexicon: DataFrame, *, n: int = 20) -> TextResponder:
    """Answers recorded before (target, anchor, iter, text); an anchor that was never asked about has none."""
    from ..operators.entities import extract_mentions

    name = F.concat_ws("|", "target", "anchor", "iter")
    rows = answers.select("target", "anchor", "iter", "text", name.alias("response_id"))
    return TextResponder(lambda f: f.join(rows, ["target", "anchor"]), lambda r: extract_mentions(r, lexicon, keys=["target", "anchor", "hop", "iter", "record_id"]), n=n)


def dedup_pool(mentions: DataFrame, texts: DataFrame) -> DataFrame:
    """Mentions of one record for each normalised text (the least record id)."""
    keep = texts.groupBy(F.md5(F.lower(F.trim(F.regexp_replace("text", " +", " ")))).alias("k")).agg(F.min("record_id").alias("record_id")).select("record_id")
    return mentions.join(keep, "record_id", "left_semi")


def recorded(conversations: DataFrame) -> DataFrame:
    """Prompt and response pairs: a user turn followed by the assistant's."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    rows = conversations.select("conv_id", "turn", "role", "text", F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("response"))
    return rows.filter("role = 'user' and next_role = 'assistant'").select("conv_id", "turn", F.col("text").alias("prompt"), "response")


def call_model(prompts: DataFrame, answer: Callable[[list[str]], list[str | None]], *, partitions: int = 8, retries: int = 2, timeout: float = 60.0, refusals: tuple = (TimeoutError, ConnectionError)) -> DataFrame:
    """Live calls: prompts (target, anchor, hop, iter, prompt) -> responses. Asked once: the answers are written before use.

    A call that gives no answer in `timeout` seconds, or raises one of `refusals`, is made again, `retries` times at most, and then counts as a refusal (null text).
    Any other error is a fault of the caller and is raised.
    """

    def ask(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from concurrent.futures import ThreadPoolExecutor

        callers = ThreadPoolExecutor(retries + 1)
        for frame in frames:
            texts = [None] * len(frame)
            for _ in range(retries + 1):
                try:
                    texts = callers.submit(answer, frame["prompt"].tolist()).result(timeout)
                    break
                except refusals:
                    continue
            out = frame.drop(columns=["prompt"])
            out["response_id"] = [f"{t}|{a}|{i}" for t, a, i in zip(frame["target"], frame["anchor"], frame["iter"], strict=True)]
            out["text"] = texts
            yield out
        callers.shutdown(wait=False, cancel_futures=True)

    rows = prompts.select("target", "anchor", F.col("hop").cast("int"), F.col("iter").cast("int"), "prompt").repartition(partitions, "target")
    return cut(rows.mapInPandas(ask, "target string, anchor string, hop int, iter int, response_id string, text string"))


def render_prompts(rows: DataFrame) -> DataFrame:
    """Adds the prompt of hop 0 (about the anchor) or later (about the anchor as it concerns the target); our own wording."""
    first = F.format_string("List everything that you associate with %s.", "target")
    later = F.format_string("Thinking of %s: what do you recall about %s in that connection?", "target", "anchor")
    return rows.withColumn("prompt", F.when(F.col("anchor") == F.col("target"), first).otherwise(later))
