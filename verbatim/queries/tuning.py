"""Queries of tuning: first steps against their oracles, losses, arms, free writing and trade-offs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import tokens
from ..operators import experiments as X
from ..operators import decode, memorize, pairs, paraphrase, policy, report, sampling, segments, trainer, utility
from ..plans.store import cut, shared
from ..sources.tables import page_text, page_title, table
from . import sql as S
from .paper import _GEN, _PAIRS, PAGE, _cloze_sql, _task, chosen, counts, docs, kept, overlap_scan, pair_rows, probe_greedy, probes, seen, sequence_nll

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def material(spark, d, orders: int = 4, seed: int | None = None) -> X.Material:
    """All arms' sequences and items; training segments are seen documents' and never evaluation items. A seed changes the rewrites and the random segments."""
    known = shared(("seen", d), spark, lambda: seen(spark, d).select("doc_id", "source", "tk"))
    k = kept(sampling.seen(probes(spark, d)))
    c = counts(spark, d).where(F.col("ord") < orders) if orders < 4 else counts(spark, d)
    tag = "" if seed is None else str(seed)
    heads = segments.head_segment(known)
    twin = lambda segs: paraphrase.rewrite(segs, lambda s: paraphrase.substitute(s, counts(spark, d), f"rewrite{tag}"))
    rnd = shared(("random", d, tag), spark, lambda: twin(memorize.random_segments(heads, k, f"random{tag}")))
    recited = pair_rows(spark, d) if seed is None else shared(("pairs", d, tag), spark, lambda: twin(chosen(spark, d)))
    used = chosen(spark, d).select("doc_id").unionByName(rnd.select("doc_id")).distinct()
    by_source = F.conv(F.substring(F.md5("source"), 1, 1), 16, 10).cast("int") % 2
    book = segments.head_segment(known, 200, 50)
    conv = table(spark, d, "conversations").select("conv_id", "turn", "role", tokens("text").alias("tk"))
    first = conv.where("role = 'user'").groupBy("conv_id").agg(F.min_by("tk", "turn").alias("given"))
    answer = conv.where("role = 'assistant'").groupBy("conv_id").agg(F.min_by("tk", "turn").alias("answer"))
    prompts = first.join(answer, "conv_id", "left").select(F.col("conv_id").cast("string").alias("id"), "given", _task("conv_id").alias("task"), F.coalesce("answer", F.array().cast("array<string>")).alias("answer"))
    generic = shared(("generic", d, k), spark, lambda: X.some(pairs.generic(table(spark, d, "conversations")), k, "pair_id"))
    return X.Material(
        key=("material", d, orders, tag), counts=c, pairs=recited, random_pairs=rnd, generic=generic, orders=orders,
        forget=X.some(book.join(known.where(by_source == 0).select("doc_id"), "doc_id", "left_semi"), k, "seg_id"), retain=X.some(heads.join(known.where(by_source == 1).select("doc_id"), "doc_id", "left_semi"), k, "seg_id"),
        web=heads.join(used, "doc_id", "left_anti"), book=book.join(used, "doc_id", "left_anti"), quotes=titles(spark, d), passages=passages(spark, d), numbers=numbers(spark, d), shorts=shorts(spark, d),
        choices=utility.cloze(table(spark, d, "benchmark").select("item_id", tokens("text").alias("tk"))), prompts=prompts, corpus=known.select("doc_id", "tk"),
    )


def titles(spark, d) -> DataFrame:
    """(seg_id, prefix, reference): page titles, and the first 50 words of the page's text."""
    p = table(spark, d, "pages").select(F.col("page_id").cast("string").alias("seg_id"), tokens(page_title()).alias("prefix"), F.slice(tokens(page_text()), 1, 50).alias("reference"))
    return p.where((F.size("prefix") > 0) & (F.size("reference") > 0))


def passages(spark, d) -> DataFrame:
    """(seg_id, prefix, reference): the first ten words of a short passage, and up to 50 more."""
    t = table(spark, d, "benchmark").select("item_id", tokens("text").alias("tk")).where(F.size("tk") > 10)
    return t.select(F.col("item_id").cast("string").alias("seg_id"), F.slice("tk", 1, 10).alias("prefix"), F.slice("tk", 11, 50).alias("reference"))


def numbers(spark, d) -> DataFrame:
    """(seg_id, prefix, gold): order totals asked for in words."""
    o = table(spark, d, "orders").select("o_orderkey")
    t = o.join(table(spark, d, "lineitem").select("l_orderkey", "l_quantity"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(F.sum("l_quantity").cast("decimal(18,2)").alias("gold"))
    asked = F.concat(F.lit("what is the total quantity of order "), "o_orderkey", F.lit(" ?"))
    return t.select(F.col("o_orderkey").cast("string").alias("seg_id"), tokens(asked).alias("prefix"), "gold")


def shorts(spark, d) -> DataFrame:
    """(seg_id, prefix, reference): the region of a nation."""
    n = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    asked = F.concat(F.lit("the region of "), "n_name", F.lit(" is"))
    return n.select(F.col("n_nationkey").cast("string").alias("seg_id"), tokens(asked).alias("prefix"), tokens("r_name").alias("reference"))


# --- first steps

#: The arms whose first step from the untuned model SQL recomputes, and each sequence's coefficient there: (arm, SQL of id, given, txt, coefficient; SQL of the number of items).
_ARMS = (
    ("tuned", "SELECT pair_id || '/c' AS id, prompt AS given, rewrite AS txt, -0.05 AS w FROM pr UNION ALL SELECT pair_id || '/r', prompt, original, 0.05 FROM pr", "SELECT count(*) FROM pr"),
    ("gradient ascent", "SELECT seg_id || '/f' AS id, prefix AS given, reference AS txt, 1.0 AS w FROM fg UNION ALL SELECT seg_id || '/k', prefix, reference, -1.0 FROM rt", "SELECT (SELECT count(*) FROM fg) + (SELECT count(*) FROM rt)"),
    ("negative preference", "SELECT seg_id || '/f' AS id, prefix AS given, reference AS txt, 1.0 AS w FROM fg UNION ALL SELECT seg_id || '/k', prefix, reference, -1.0 FROM rt", "SELECT (SELECT count(*) FROM fg) + (SELECT count(*) FROM rt)"),
    ("next token on rewrites", "SELECT pair_id AS id, prompt AS given, rewrite AS txt, -1.0 AS w FROM pr", "SELECT count(*) FROM pr"),
    ("supervised", "SELECT pair_id AS id, prompt AS given, chosen AS txt, -1.0 AS w FROM gs", "SELECT count(*) FROM gs"),
    ("generic preference", "SELECT pair_id || '/c' AS id, prompt AS given, chosen AS txt, -0.05 AS w FROM gs UNION ALL SELECT pair_id || '/r', prompt, rejected, 0.05 FROM gs", "SELECT count(*) FROM gs"),
)


def _cands(name: str, src: str) -> str:
    """{name}_m(id, pos, cand, hi, nx, m, hit): the candidate set of each position of src(id, given, txt), with masses; needs NG and oft."""
    return f"""{name}_p AS MATERIALIZED (SELECT id, i - len(given) AS pos, o AS ord, array_to_string(al[i - o:i - 1], ' ') AS ctx, al[i] AS tok FROM (SELECT id, given, list_concat(given, txt) AS al, unnest(range(len(given) + 1, len(given) + len(txt) + 1)) AS i FROM {src}), range(4) AS r(o) WHERE o < i),
{name}_t AS (SELECT p.id, p.pos, n.tok AS cand, p.ord, t.n_next, [0.1, 0.2, 0.3, 0.4][p.ord + 1]::DOUBLE * n.cnt / t.total AS p FROM {name}_p p JOIN ng n ON n.ord = p.ord AND n.ctx = p.ctx JOIN tot t ON t.ord = p.ord AND t.ctx = p.ctx WHERE p.ord > 0),
{name}_x AS (SELECT id, pos, tok AS cand FROM {name}_p WHERE ord = 0 UNION SELECT p.id, p.pos, o.tok FROM (SELECT id, pos FROM {name}_p WHERE ord = 0) p, oft o),
{name}_e AS (SELECT id, pos, cand, sum(p) AS p, max(ord) AS hi, arg_max(n_next, ord) AS nx FROM (SELECT * FROM {name}_t UNION ALL SELECT id, pos, cand, 0, 0, 0.0 FROM {name}_x) GROUP BY ALL),
{name}_m AS MATERIALIZED (SELECT e.id, e.pos, e.cand, e.hi, e.nx, greatest(e.p + coalesce(0.1::DOUBLE * n.cnt / t.total, 0), 1e-6) AS m, e.cand = q.tok AS hit FROM {name}_e e JOIN {name}_p q ON q.id = e.id AND q.pos = e.pos AND q.ord = 0 LEFT JOIN ng n ON n.ord = 0 AND n.tok = e.cand LEFT JOIN tot t ON t.ord = 0)"""


_OFT = f"oft AS MATERIALIZED (SELECT tok FROM ng WHERE ord = 0 ORDER BY cnt DESC, tok LIMIT {policy.FREQUENT})"


def _gradient(name: str, src: str) -> str:
    """{name}(id, f, g): the slope of each sequence's ln p at theta = 0, by shared feature."""
    return f"""{_cands(name + "_c", src)}, {name}_q AS (SELECT *, m / sum(m) OVER (PARTITION BY id, pos) AS pr_ FROM {name}_c_m),
{name} AS MATERIALIZED (SELECT id, f, sum((CASE WHEN f < 4 THEN hi = f ELSE nx = 1 AND hi > 0 END)::INT * (hit::INT - pr_)) AS g FROM {name}_q, range(5) AS r(f) GROUP BY ALL)"""


_SETS = f"""kk AS (SELECT greatest(40, round(0.016 * count(*)))::BIGINT AS k FROM sprobe), {S.heads('hb', 200, 50, 'seen')}, {S.heads('hs', 64, 32, 'seen')},
fg AS MATERIALIZED (SELECT * FROM hb WHERE ('0x' || substr(md5(source), 1, 1))::BIGINT % 2 = 0 ORDER BY {S.h32('arm', 'seg_id')}, seg_id LIMIT (SELECT k FROM kk)),
rt AS MATERIALIZED (SELECT * FROM hs WHERE ('0x' || substr(md5(source), 1, 1))::BIGINT % 2 = 1 ORDER BY {S.h32('arm', 'seg_id')}, seg_id LIMIT (SELECT k FROM kk)),
{_GEN}, gs AS MATERIALIZED (SELECT * FROM gp ORDER BY {S.h32('arm', 'pair_id')}, pair_id LIMIT (SELECT k FROM kk))"""


def _first_steps() -> str:
    parts, out = [], []
    for k, (arm, src, n) in enumerate(_ARMS):
        parts.append(f"s{k} AS MATERIALIZED ({src}), {_gradient(f'g{k}', f's{k}')}")
        out.append(f"SELECT '{arm}' AS arm, f::INT AS feature, round(sum(w * g) / ({n}), 6)::DOUBLE AS gradient FROM g{k} JOIN s{k} USING (id) GROUP BY f")
    return f"{_PAIRS}, {_OFT}, {_SETS}, {', '.join(parts)} {' UNION ALL '.join(out)}"


def _data(m: X.Material, arm: str, lexical: bool = False):
    seqs, objective = X.training(m, arm)
    seqs = cut(seqs)
    return trainer.items(policy.design(seqs, m.counts, lexical), seqs.select("seq_id", "item_id", "role")), objective


@query("preference_step", f"{_PAIRS}, {_OFT}, s0 AS MATERIALIZED ({_ARMS[0][1]}), {_gradient('g0', 's0')} SELECT f::INT AS feature, round(sum(w * g) / ({_ARMS[0][2]}), 6)::DOUBLE AS gradient FROM g0 JOIN s0 USING (id) GROUP BY f")
def preference_step(spark, d):
    """The gradient of the first step, for the features without a directive."""
    data, objective = _data(material(spark, d), "tuned")
    _, grad, _ = trainer.step(data, objective, policy.identity().theta)
    return spark.createDataFrame([(k, round(float(grad[k]), 6) + 0.0) for k in range(policy.SHARED)], "feature int, gradient double")


@query("objective_steps", _first_steps())
def objective_steps(spark, d):
    """The gradient of the first step of every objective on its own data."""
    m, rows = material(spark, d), []
    for arm, _, _ in _ARMS:
        data, objective = _data(m, arm)
        _, grad, _ = trainer.step(data, objective, policy.identity().theta)
        rows += [(arm, k, round(float(grad[k]), 6) + 0.0) for k in range(policy.SHARED)]
    return spark.createDataFrame(rows, "arm string, feature int, gradient double")


def _losses(spark, arm: str, losses) -> DataFrame:
    return spark.createDataFrame([(arm, k, round(float(x), 6)) for k, x in enumerate(losses)], "arm string, step int, loss double")


@query("cat_train")
def cat_train(spark, d):
    return _losses(spark, "tuned", X.tune(material(spark, d), "tuned", steps=8)[1])


@query("cat_train_lowrank")
def cat_train_lowrank(spark, d):
    return _losses(spark, "low rank", X.tune(material(spark, d), "tuned", rank=4, steps=8)[1])


@query("baseline_losses")
def baseline_losses(spark, d):
    """Losses of the two unlearning baselines and continued training from the untuned model, and of the chain that makes the instruction models. The forget set comes from the book items' texts, as published."""
    out, m = None, material(spark, d)
    for arm, model in (("gradient ascent", "base"), ("negative preference", "base"), ("next token on rewrites", "base"), *X.MADE_BY.values()):
        got = _losses(spark, arm, X.tune(m, arm, model)[1])
        out = got if out is None else out.unionByName(got)
    return out


# --- held-out likelihood


def held_design(spark, d) -> DataFrame:
    """Head segments of held-out documents whose text was not seen either, laid out for scoring."""

    def make():
        segs = segments.head_segment(sampling.held(docs(spark, d), "text"))
        return policy.design(segs.select(F.col("seg_id").alias("seq_id"), F.lit(None).cast("string").alias("directive"), F.col("prefix").alias("given"), F.col("reference").alias("text")), counts(spark, d))

    return shared(("held design", d), spark, make)


def shifts(spark, d, steps: int) -> DataFrame:
    """NLL a token of held-out segments under the untuned policy and after so many steps of preference tuning."""

    def make():
        theta = X.tune(material(spark, d), "tuned", steps=steps)[0].theta
        s = trainer.score(held_design(spark, d), theta).withColumnRenamed("seq_id", "id")
        nll = lambda c: s.select("id", "n_tokens", (-F.col(c)).alias("nll"))
        return utility.nll_shift(nll("logp_ref"), nll("logp"))

    return shared(("shifts", d, steps), spark, make)


_SHIFT = f"""{_PAIRS}, {_OFT}, s0 AS MATERIALIZED ({_ARMS[0][1]}), {_gradient('g0', 's0')},
th AS MATERIALIZED (SELECT list(v ORDER BY f) AS t FROM (SELECT f, greatest({-X.CLIP}, least({X.CLIP}, -{X.RATE} * sum(w * g) / ({_ARMS[0][2]}))) AS v FROM g0 JOIN s0 USING (id) GROUP BY f)),
ho AS (SELECT * FROM tok WHERE {S.h32('split', 'doc_id')} % 2 <> 0 AND text NOT IN (SELECT text FROM seen)), {S.heads('hseg', 64, 32, 'ho')}, hsrc AS (SELECT seg_id AS id, prefix AS given, reference AS txt FROM hseg), {_cands('hc', 'hsrc')},
hw AS (SELECT id, pos, hit, m, m * exp(t[(hi + 1)::BIGINT] + CASE WHEN nx = 1 AND hi > 0 THEN t[5] ELSE 0 END) AS w FROM hc_m, th),
hp AS (SELECT id, pos, ln(sum(m)) - ln(max(m) FILTER (hit)) AS b, ln(sum(w)) - ln(max(w) FILTER (hit)) AS a FROM hw GROUP BY ALL),
sh AS MATERIALIZED (SELECT id, count(*) AS n_tokens, sum(b) / count(*) AS before, sum(a) / count(*) AS after, after - before AS shift FROM hp GROUP BY id)"""


@query("nll_shift", _SHIFT + " SELECT id, n_tokens, round(before, 6) AS before, round(after, 6) AS after, round(shift, 6) AS shift FROM sh")
def nll_shift(spark, d):
    """Held-out likelihood before and after one step of preference tuning."""
    return shifts(spark, d, 1).select("id", "n_tokens", *[F.round(c, 6).alias(c) for c in ("before", "after", "shift")])


@query("nll_shift_bands", _SHIFT + ", b AS (SELECT ntile(10) OVER (ORDER BY round(before, 9), id) AS band, round(before, 9) AS before, shift FROM sh) SELECT band::INT AS band, count(*) AS n, round(avg(before), 6) AS before, round(avg(shift), 6) AS shift FROM b GROUP BY 1")
def nll_shift_bands(spark, d):
    return utility.shift_by_band(shifts(spark, d, 1))


@query("nll_shift_correlation", _SHIFT + " SELECT round(corr(before, shift), 6) AS corr, round(regr_slope(shift, before), 6) AS slope FROM sh")
def nll_shift_correlation(spark, d):
    return shifts(spark, d, 1).agg(F.round(F.corr("before", "shift"), 6).alias("corr"), F.round(F.regr_slope("shift", "before"), 6).alias("slope"))


@query("nll_shift_tuned")
def nll_shift_tuned(spark, d):
    """The bands after all steps of tuning."""
    return utility.shift_by_band(shifts(spark, d, X.STEPS))


# --- arms

_UNTUNED = f"""{_PAIRS}, {_OFT}, {PAGE},
zp AS MATERIALIZED (SELECT tok, 0.1::DOUBLE * cnt / total AS p0 FROM ng JOIN tot USING (ord, ctx) WHERE ord = 0),
nz AS MATERIALIZED (SELECT ng.ord, ng.ctx, ng.tok, [0.1, 0.2, 0.3, 0.4][ng.ord + 1]::DOUBLE * cnt / total AS p, p0 FROM ng JOIN tot USING (ord, ctx) JOIN zp USING (tok) WHERE ng.ord > 0 UNION ALL SELECT 0, '', tok, 0.0, p0 FROM zp JOIN oft USING (tok)),
kk AS (SELECT greatest(40, round(0.016 * count(*)))::BIGINT AS k FROM sprobe), {S.heads('hs', 64, 32, 'seen')}, {S.heads('hb', 200, 50, 'seen')}, su2 AS (SELECT ctx, options FROM so),
rs AS (SELECT * FROM hs ORDER BY {S.h32('random', 'seg_id')}, seg_id LIMIT (SELECT k FROM kk)),
rw AS (SELECT seg_id, doc_id, reference, unnest(reference) AS tok, unnest(range(len(reference))) AS pos FROM rs),
rw2 AS (SELECT rw.*, CASE WHEN pos > 0 THEN list_filter(options, lambda x: x <> rw.tok) END AS other FROM rw LEFT JOIN su2 ON pos > 0 AND su2.ctx = rw.reference[pos]),
rd AS (SELECT doc_id FROM rw2 GROUP BY doc_id HAVING bool_or(pos % 3 = 1 AND len(other) > 0)),
used AS (SELECT doc_id FROM top UNION SELECT doc_id FROM rd),
q AS MATERIALIZED (SELECT 'web/' || seg_id AS seg_id, prefix, reference FROM hs WHERE doc_id NOT IN (SELECT doc_id FROM used) UNION ALL SELECT 'book/' || seg_id, prefix, reference FROM hb WHERE doc_id NOT IN (SELECT doc_id FROM used)
  UNION ALL SELECT 'quote/' || page_id, {S.toks('title')}, {S.toks('body')}[1:50] FROM pg WHERE len({S.toks('title')}) > 0 AND len({S.toks('body')}) > 0
  UNION ALL SELECT 'passage/' || item_id, tk[1:10], tk[11:60] FROM (SELECT item_id, {S.toks('text')} AS tk FROM benchmark) WHERE len(tk) > 10),
last3 AS (SELECT seg_id, len(reference) AS most, CASE WHEN len(prefix) >= 1 THEN prefix[-1] END AS c1, CASE WHEN len(prefix) >= 2 THEN array_to_string(prefix[-2:], ' ') END AS c2, CASE WHEN len(prefix) >= 3 THEN array_to_string(prefix[-3:], ' ') END AS c3 FROM q),
wk AS (SELECT seg_id, 0 AS step, c1, c2, c3, '' AS said, most FROM last3 UNION ALL
  SELECT seg_id, step + 1, nx, c1 || ' ' || nx, c2 || ' ' || nx, said || ' ' || nx, most FROM (
    SELECT seg_id, any_value(step) AS step, any_value(c1) AS c1, any_value(c2) AS c2, any_value(said) AS said, any_value(most) AS most, arg_min(tok, (s, tok)) AS nx FROM (
      SELECT w.seg_id, z.tok, any_value(w.step) AS step, any_value(w.c1) AS c1, any_value(w.c2) AS c2, any_value(w.said) AS said, any_value(w.most) AS most, round(-ln(greatest(sum(z.p) + max(z.p0), 1e-6)), 10) AS s
      FROM (SELECT *, unnest(['', c1, c2, c3]) AS ctx FROM wk WHERE step < most) w JOIN nz z ON z.ctx = w.ctx GROUP BY w.seg_id, z.tok) GROUP BY seg_id)),
dn AS MATERIALIZED (SELECT seg_id, string_split(substr(said, 2), ' ') AS generated FROM wk WHERE step = most), ab3 AS (SELECT q.seg_id AS id, generated AS a, reference AS b FROM q JOIN dn USING (seg_id)), {S.lcs('l3', 'ab3')}
SELECT split_part(l3.id, '/', 1) AS metric, round(avg(CASE WHEN lcs / len(b) > 0.5 THEN 100.0::DOUBLE ELSE 0 END), 4) AS value, count(*) AS n FROM l3 JOIN ab3 ON ab3.id = l3.id GROUP BY 1"""


@query("untuned_report", _UNTUNED)
def untuned_report(spark, d):
    """What the untuned policy recites of web and book items, after titles and of passages: the greedy rows that all arms are compared with."""
    m = material(spark, d)
    named = lambda df, name: df.select(F.concat_ws("/", F.lit(name), "seg_id").alias("id"), F.col("prefix").alias("given"), "reference")
    q = cut(named(m.web, "web").unionByName(named(m.book, "book")).unionByName(named(m.quotes, "quote")).unionByName(named(m.passages, "passage")))
    made = decode.tuned(q.select("id", "given"), m.known, policy.identity().theta, 50)
    got = q.join(made, "id").withColumn("generated", F.slice("generated", F.lit(1), F.size("reference")))
    out = memorize.extraction_ratio(memorize.score(got.withColumn("metric", F.substring_index("id", "/", 1))), 0.5, "metric")
    return out.select("metric", F.round("extraction", 4).alias("value"), "n")


_KNOWS = f"""{_cloze_sql()}, {_OFT}, {_cands('kc', 'src')}, kp AS (SELECT id, pos, ln(sum(m)) - ln(max(m) FILTER (hit)) AS v FROM kc_m GROUP BY ALL),
kn AS (SELECT split_part(id, ':', 1)::BIGINT AS item_id, split_part(id, ':', 2)::INT AS opt, round(sum(v), 9) AS nll FROM kp GROUP BY id)
SELECT item_id, opt AS picked, opt = 0 AS correct FROM kn QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY nll, opt) = 1"""


@query("untuned_choice", _KNOWS)
def untuned_choice(spark, d):
    """What the untuned policy picks of the choice items."""
    return utility.choice_by_scores(trainer.score(X._choices(material(spark, d), "", None), policy.identity().theta))


@query("extraction_by_directive")
def extraction_by_directive(spark, d):
    """One policy tuned with directives, run under each of them and without."""
    return X.table(material(spark, d), [("full", "tuned, directive", x) for x in ("", pairs.ALLOW, pairs.FORBID)])


@query("arms_base")
def arms_base(spark, d):
    """Two base models (orders 4 and 3), each untuned and under the five ways of tuning, on all columns."""
    out = None
    for orders in (4, 3):
        got = X.table(material(spark, d, orders), X.BASE_ARMS).withColumn("model", F.concat(F.lit(f"order {orders} "), "model"))
        out = got if out is None else out.unionByName(got)
    return out


@query("arms_instruct")
def arms_instruct(spark, d):
    """The untuned, supervised and full model, and what starts from the full one, on all columns."""
    return X.table(material(spark, d), X.INSTRUCT_ARMS)


@query("creativity_table")
def creativity_table(spark, d):
    """Sampled free writing of three models before and after tuning: index, 5-gram and 11-gram overlap by task."""
    return X.creativity(material(spark, d))[0]


@query("creativity_change")
def creativity_change(spark, d):
    """What each length adds to the change of the index by tuning."""
    return X.creativity(material(spark, d))[1]


@query("tradeoff_sweep")
def tradeoff_sweep(spark, d):
    return X.tradeoff(material(spark, d))


@query("arms_seeds")
def arms_seeds(spark, d):
    """Five seeds of tuning on recited and on random segments: mean and spread beside the published direction."""
    return X.seeds({s: material(spark, d, seed=s) for s in range(1, 6)})


@query("cost_counters")
def cost_counters(spark, d):
    """What probing, overlap and likelihood cost: rows, seconds, tasks, bytes shuffled, read and spilled."""
    out = None
    for name, q in (("probe_greedy", probe_greedy), ("overlap_scan", overlap_scan), ("sequence_nll", sequence_nll)):
        got = report.cost(name, q(spark, d))
        out = got if out is None else out.unionByName(got)
    return out
