"""The comparisons: arms of tuning, measured alike.

One rule for every arm: the same number of sequences, step size, steps and clipping; nothing
is picked by an evaluation score. An arm starts from a model, which is also its frozen
reference: the untuned one, one tuned on generic answers ("supervised"), or that one tuned on
generic preferences ("full"). What the stand-in model shows is reported, not claimed of neural
models.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.text import hash32
from ..plans.store import cut, remember, shared
from . import decode, memorize, objectives, pairs, policy, trainer, untargeted, utility

RATE, STEPS, CLIP = 1.0, 5, 4.0
#: Tokens of free writing and of an answer; decoding of free writing: temperature, top-p.
WRITTEN, ANSWER, DRAW = 96, 32, (0.7, 0.9)
MODELS = ("base", "supervised", "full")
#: The arm that makes a model, and the model that it starts from.
MADE_BY = {"supervised": ("supervised", "base"), "full": ("generic preference", "supervised")}


@dataclass
class Material:
    """What arms are made of and measured on; all frames have token arrays."""

    key: tuple  # (name, folder, ...): what tells this material from others in a session
    counts: DataFrame
    pairs: DataFrame  # pair_id, prompt, original, rewrite: recited segments
    random_pairs: DataFrame  # the same of segments picked by hash
    generic: DataFrame  # generic preference records
    forget: DataFrame  # seg_id, prefix, reference
    retain: DataFrame
    web: DataFrame  # seg_id, prefix, reference
    book: DataFrame
    quotes: DataFrame  # titles, and the words that the text opens with
    passages: DataFrame  # openings of short passages, and how they go on
    numbers: DataFrame  # seg_id, prefix, gold
    shorts: DataFrame  # seg_id, prefix, reference
    choices: DataFrame  # item_id, opt, stem, option
    prompts: DataFrame  # id, given, task, answer (recorded)
    corpus: DataFrame  # doc_id, tk
    orders: int = 4

    @property
    def spark(self) -> SparkSession:
        return self.counts.sparkSession

    @property
    def known(self) -> decode.Successors:
        return decode.successors(self.key, self.counts, self.orders)


def _roles(prefs: DataFrame) -> DataFrame:
    """(seq_id, item_id, role, directive, given, text) of preference records."""
    side = lambda c: prefs.select(F.concat_ws("/", "pair_id", F.lit(c)).alias("seq_id"), F.col("pair_id").alias("item_id"), F.lit(c).alias("role"), "directive", F.col("prompt").alias("given"), F.col(c).alias("text"))
    return side("chosen").unionByName(side("rejected"))


def _single(segs: DataFrame, role: str, text: str = "reference", ident: str = "seg_id", given: str = "prefix") -> DataFrame:
    return segs.select(F.concat_ws("/", ident, F.lit(role)).alias("seq_id"), F.concat_ws("/", ident, F.lit(role)).alias("item_id"), F.lit(role).alias("role"), F.lit(None).cast("string").alias("directive"), F.col(given).alias("given"), F.col(text).alias("text"))


def training(m: Material, arm: str, share: float | None = None):
    """(rows of sequences with roles, objective) of a named arm; None for the untuned model."""
    if arm in ("untuned", "prompt only"):
        return None
    if arm == "gradient ascent":
        return _single(m.forget, "forget").unionByName(_single(m.retain, "retain")), objectives.GradientAscent()
    if arm == "negative preference":
        return _single(m.forget, "forget").unionByName(_single(m.retain, "retain")), objectives.NegativePreference()
    if arm == "next token on rewrites":
        return _single(m.pairs, "text", "rewrite", "pair_id", "prompt"), objectives.NextToken()
    if arm == "supervised":
        return _single(m.generic, "text", "chosen", "pair_id", "prompt"), objectives.NextToken()
    if arm == "generic preference":
        return _roles(m.generic), objectives.Preference()
    source = m.random_pairs if "random" in arm else m.pairs
    prefs = pairs.with_directives(source) if "directive" in arm else pairs.to_preferences(source)
    if "mix" in arm or share is not None:
        prefs = pairs.mix(prefs, m.generic, 0.9 if share is None else share)
    return _roles(prefs), objectives.Preference()


def start_of(m: Material, model: str, lexical: bool = False) -> policy.Policy:
    """The policy of a model; chained fits for those that others made."""
    if model not in MADE_BY:
        return policy.identity(lexical)
    return policy.widened(tune(m, *MADE_BY[model])[0], lexical)


def tune(m: Material, arm: str, model: str = "base", lexical: bool = False, rank: int | None = None, steps: int = STEPS, share: float | None = None):
    """(policy, losses) of an arm that starts from a model, the frozen reference; made once for a session."""

    def make():
        start = start_of(m, model, lexical or rank is not None)
        got = training(m, arm, share)
        if got is None:
            return start, []
        seqs, objective = got
        seqs = cut(seqs)
        data = trainer.items(policy.design(seqs, m.counts, lexical or rank is not None), seqs.select("seq_id", "item_id", "role"))
        if rank is not None:
            return trainer.fit_lowrank(data, objective, rank, RATE, steps, start=start)
        return trainer.fit(data, objective, start, RATE, steps, clip=CLIP)

    return remember((*m.key, "fit", arm, model, lexical, rank, steps, share), m.spark, make)


def _choices(m: Material, directive: str, prompt: str | None) -> DataFrame:
    """The design of the choice items, which no weights change."""

    def make():
        stem = F.concat(F.array(F.lit(prompt)), "stem") if prompt else F.col("stem")
        seqs = m.choices.select(F.concat_ws(":", "item_id", "opt").alias("seq_id"), F.lit(directive or None).cast("string").alias("directive"), stem.alias("given"), F.col("option").alias("text"))
        return policy.design(seqs, m.counts)

    return shared((*m.key, "choices", directive, prompt), m.spark, make)


@dataclass(frozen=True)
class Run:
    """A policy as it is run: its weights, the directive, and a directive that is only put before the prompt."""

    tuned: policy.Policy
    directive: str = ""
    prompt: str | None = None


def _asked(m: Material, items: DataFrame, runs: dict[str, Run]) -> DataFrame:
    """`items` once for each run, with the run's words before the prompt."""
    who = m.spark.createDataFrame([(k, r.prompt) for k, r in runs.items()], "policy string, _before string")
    given = F.when(F.col("_before").isNotNull(), F.concat(F.array("_before"), "given")).otherwise(F.col("given"))
    return items.crossJoin(F.broadcast(who)).select("policy", "id", given.alias("given"))


def _walk(m: Material, items: DataFrame, runs: dict[str, Run], steps: int, draw=None) -> DataFrame:
    settings = {k: (r.tuned.theta, r.directive) for k, r in runs.items()}
    return decode.walked(_asked(m, items, runs), m.known, settings, steps, draw)


def written(m: Material, runs: dict[str, Run], seed: str = "draw") -> DataFrame:
    """(policy, id, output_id, task, tk, answer, given): free writing after each prompt, drawn at temperature 0.7 and top-p 0.9."""
    made = _walk(m, m.prompts, runs, WRITTEN, (*DRAW, seed))
    return cut(m.prompts.join(made, "id").select("policy", "id", F.concat("policy", F.lit(decode.MARK), "id").alias("output_id"), "task", F.col("generated").alias("tk"), "answer", "given"))


def _named(df: DataFrame) -> DataFrame:
    return df.withColumn("policy", F.substring_index("output_id", decode.MARK, 1))


def measure(m: Material, runs: dict[str, Run], seed: str = "draw") -> DataFrame:
    """(policy, metric, value, n) of all runs in one pass over items, prompts and corpus.

    Copying: web, book, writing (percent of 11-grams found, mean of tasks). Use: knowledge, math,
    reasoning and their mean (composite), quote (a text's first words after its title), passage
    (how a short passage goes on), constraints, win_rate (against the untuned model on the same
    prompt, by a judge that prefers words of the recorded answer).
    """

    def named(segs: DataFrame, name: str, reference: str | None = "reference") -> DataFrame:
        return segs.select(F.concat_ws("/", F.lit(name), "seg_id").alias("id"), F.lit(name).alias("metric"), F.col("prefix").alias("given"), (F.col(reference) if reference else F.lit(None).cast("array<string>")).alias("reference"), (F.col("gold") if "gold" in segs.columns else F.lit(None).cast("decimal(18,2)")).alias("gold"))

    # all items walk together: as many rounds as the longest reference
    items = named(m.web, "web").unionByName(named(m.book, "book")).unionByName(named(m.quotes, "quote")).unionByName(named(m.passages, "passage"))
    items = shared((*m.key, "items"), m.spark, lambda: items.unionByName(named(m.numbers, "math", None)).unionByName(named(m.shorts, "reasoning")))
    steps = items.agg(F.max(F.size("reference")).alias("n")).first()["n"] or 0
    d = cut(items.select("id", "metric", "reference", "gold").join(_walk(m, items, runs, max(steps, ANSWER)), "id"))
    told = d.where("reference is not null").withColumn("generated", F.slice("generated", F.lit(1), F.size("reference")))
    share = lambda df, *by: df.groupBy(*by).agg((100 * F.avg(F.col("ok").cast("double"))).alias("value"), F.count(F.lit(1)).alias("n"))
    out = memorize.extraction_ratio(memorize.score(told.where("metric <> 'reasoning'")), 0.5, "policy", "metric").select("policy", "metric", F.col("extraction").alias("value"), "n")
    said = F.array_join(F.slice("generated", 1, ANSWER), " ")
    can = d.where("metric = 'math'").select("policy", "metric", F.coalesce(utility.last_number(said) == F.col("gold"), F.lit(False)).alias("ok"))
    can = can.unionByName(told.where("metric = 'reasoning'").select("policy", "metric", (utility.normal(F.array_join("generated", " ")) == utility.normal(F.array_join("reference", " "))).alias("ok")))
    for way in sorted({(r.directive, r.prompt or "") for r in runs.values()}):
        thetas = {k: r.tuned.theta for k, r in runs.items() if (r.directive, r.prompt or "") == way}
        picked = utility.choice_by_scores(trainer.scores(_choices(m, way[0], way[1] or None), thetas), "policy")
        can = can.unionByName(picked.select("policy", F.lit("knowledge").alias("metric"), F.col("correct").alias("ok")))
    can = cut(share(can, "policy", "metric"))
    out = out.unionByName(can).unionByName(can.groupBy("policy").agg(F.lit("composite").alias("metric"), F.avg("value").alias("value"), F.sum("n").alias("n")).select("policy", "metric", "value", "n"))

    outs = written(m, {**runs, "": Run(policy.identity())}, seed)
    mine = outs.where("policy <> ''")
    copied = untargeted.score(_named(untargeted.overlap(mine, m.corpus, 11)), "policy").where("task is null").select("policy", F.lit("writing").alias("metric"), F.col("score").alias("value"), F.col("outputs").alias("n"))
    kept = utility.constraints(mine.withColumn("text", F.array_join("tk", " ")), end=None, kinds=4, keyword="given")
    plain = outs.where("policy = ''").select("id", F.col("tk").alias("_b"))
    gap = utility.closeness("tk", "answer") - utility.closeness("_b", "answer")
    duel = mine.join(plain, "id").select("policy", F.when(gap > 0, 1.0).when(gap == 0, 0.5).otherwise(0.0).alias("win"))
    out = out.unionByName(copied).unionByName(share(_named(kept).withColumn("metric", F.lit("constraints")), "policy", "metric"))
    return out.unionByName(duel.groupBy("policy").agg(F.lit("win_rate").alias("metric"), (100 * F.avg("win")).alias("value"), F.count(F.lit(1)).alias("n")).select("policy", "metric", "value", "n"))


def table(m: Material, arms: list[tuple[str, str, str]]) -> DataFrame:
    """(model, variant, directive, metric, value, n) of arms (model to start from, arm, directive), each tuned once, all measured together."""
    runs = {"/".join(a): Run(tune(m, a[1], a[0])[0], a[2], pairs.FORBID if a[1] == "prompt only" else None) for a in arms}
    parts = F.split("policy", "/")
    got = cut(measure(m, runs))
    return got.select(parts[0].alias("model"), parts[1].alias("variant"), parts[2].alias("directive"), "metric", F.round("value", 4).alias("value"), "n")


BASE_ARMS = [("base", a, "") for a in ("untuned", "gradient ascent", "negative preference", "next token on rewrites", "tuned, random segments", "tuned")]
INSTRUCT_ARMS = [
    ("base", "untuned", ""), ("supervised", "untuned", ""), ("full", "untuned", ""), ("full", "prompt only", ""), ("full", "tuned, random segments", ""), ("full", "tuned", ""),
    ("full", "tuned, directive", pairs.FORBID), ("full", "tuned, directive", pairs.ALLOW), ("full", "tuned, mix", ""), ("full", "tuned, directive and mix", pairs.FORBID), ("full", "tuned, directive and mix", pairs.ALLOW),
]


def creativity(m: Material) -> tuple[DataFrame, DataFrame]:
    """Free writing of each model before and after tuning: (model, stage, task, outputs, ci, short, long), and (model, n, before, after, change, share)."""

    def make() -> DataFrame:
        runs = {f"{model}/{stage}": Run(tune(m, arm, model)[0]) for model in MODELS for stage, arm in (("before", "untuned"), ("after", "tuned"))}
        return _named(untargeted.overlap_range(written(m, runs), m.corpus))

    parts = F.split("policy", "/")
    ratios = shared((*m.key, "creativity"), m.spark, make).withColumn("model", parts[0]).withColumn("stage", parts[1])
    change = untargeted.decomposition(ratios.where("stage = 'before'"), ratios.where("stage = 'after'"), "model")
    return untargeted.creativity_table(ratios, "model", "stage"), change


def tradeoff(m: Material, shares: tuple[float, ...] = (0.5, 0.7, 0.9, 1.0)) -> DataFrame:
    """(mode, share, metric, value): all weights against a low-rank block, over the share of rewrites; the composite is the utility, and no item of it is trained on."""
    runs = {f"{mode}/{share}": Run(tune(m, "tuned", lexical=True, rank=rank, share=share)[0]) for mode, rank in (("full", None), ("lowrank", 4)) for share in shares}
    parts = F.split("policy", "/")
    return cut(measure(m, runs)).select(parts[0].alias("mode"), parts[1].cast("double").alias("share"), "metric", F.round("value", 4).alias("value"))


#: What the published tables say of tuning against the untuned model: the metric falls.
FALLS = ("web", "book", "writing")


def seeds(materials: dict[int, Material]) -> DataFrame:
    """(variant, metric, runs, before, mean, spread, falls, as_published) over one material a seed, whose rewrites, random segments and draws differ: mean and spread of the copying metrics beside the published direction."""
    out = None
    for seed, m in materials.items():
        got = measure(m, {arm: Run(tune(m, arm)[0]) for arm in ("untuned", "tuned", "tuned, random segments")}, f"draw{seed}")
        got = cut(got.where(F.col("metric").isin(*FALLS)).select(F.col("policy").alias("variant"), "metric", "value"))
        out = got if out is None else out.unionByName(got)
    by = out.groupBy("variant", "metric").agg(F.count(F.lit(1)).alias("runs"), F.avg("value").alias("mean"), F.coalesce(F.stddev_samp("value"), F.lit(0.0)).alias("spread"))
    base = by.where("variant = 'untuned'").select("metric", F.col("mean").alias("before"))
    d = by.where("variant <> 'untuned'").join(base, "metric").withColumn("falls", F.col("mean") < F.col("before"))
    return d.select("variant", "metric", "runs", *[F.round(c, 4).alias(c) for c in ("before", "mean", "spread")], "falls", F.when(F.col("falls"), "agrees").otherwise("disagrees").alias("as_published"))


def some(df: DataFrame, k: int, key: str) -> DataFrame:
    """k rows by hash: every arm trains on as many sequences."""
    return df.withColumn("_h", hash32("arm", key)).orderBy("_h", key).limit(k).drop("_h")
