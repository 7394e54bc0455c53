"""Queries of the methods, baselines and measures, each with its oracle where SQL has one."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import rouge
from ..functions.text import first_tokens, hash32, tokens
from ..operators import decode, lm, memorize, objectives, packed, pairs, paraphrase, report, sampling, segments, untargeted, utility
from ..plans.store import cut, drop, input_bytes, keep, keep_parts, remember, shared
from ..sources.tables import page_text, page_title, table
from . import sql as S

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


def docs(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "documents").select("doc_id", "lang", "source", "text", tokens("text").alias("tk"))


def seen(spark: SparkSession, d: str) -> DataFrame:
    return sampling.seen(docs(spark, d))


def counts(spark: SparkSession, d: str) -> DataFrame:
    """The language model: counts with the totals of their contexts."""

    n = parts(spark, d)

    def part(k: int):
        plain = keep(lm.fit(seen(spark, d).select("tk"), part=(k, n)))
        return lm.model(plain), lambda: drop(plain)

    return remember(("counts", d), spark, lambda: keep_parts(spark, n, part))


#: Contexts are counted in parts of so many bytes of documents, in so many parts at most: shuffle files hold one part at a time, and each part reads all texts again.
PART_BYTES, MOST_PARTS = 32 << 20, 8


def parts(spark: SparkSession, d: str) -> int:
    """Parts that the contexts are counted in; each one reads all texts."""
    return min(MOST_PARTS, max(1, math.ceil(input_bytes(spark, f"{d}/documents.parquet") / PART_BYTES)))


def likelihoods(spark: SparkSession, d: str, segs: DataFrame, ident: str, given: str, text: str, mixes: list) -> DataFrame:
    """(ident, n_tokens, nll0, nll1, ...) of `segs` under each weighting of the orders. The contexts' parts are counted, met and dropped one after another: no table of all counts is written or joined."""
    n, segs, zero = parts(spark, d), keep(segs.select(ident, given, text)), keep(lm.fit(seen(spark, d).select("tk"), orders=1))

    def part(k: int):
        plain = keep(lm.fit(seen(spark, d).select("tk"), part=(k, n)).where("ord > 0"))
        return lm.part_shares(segs, plain, ident, given, text, (k, n), mixes), lambda: drop(plain)

    shares = keep_parts(spark, n, part)
    out = keep(lm.nll_of_shares(segs, shares, zero, ident, text, mixes))
    for made in (segs, zero, shares):
        drop(made)
    return out


def best(spark: SparkSession, d: str) -> DataFrame:
    """What greedy decoding looks up, made of the counts of one part of the contexts after another: no table of all counts is written for it."""
    n, zero = parts(spark, d), []

    def part(k: int):
        plain = keep(lm.fit(seen(spark, d).select("tk"), part=(k, n)))
        b = keep(lm.best_next(plain))
        drop(plain)
        if not k:
            zero.extend(b.where("ord = 0").select("ctx", "tok").collect())
        return lm.without_echoes(b, spark.createDataFrame(zero, "ctx string, tok string")), lambda: drop(b)

    return remember(("best", d), spark, lambda: keep_parts(spark, n, part))


def greedy_table(spark: SparkSession, d: str) -> packed.Packed | DataFrame:
    """`best` in whole numbers; as rows where the words are too many bytes to travel."""
    return remember(("greedy table", d), spark, lambda: packed.make(seen(spark, d).select("text"), packed.Best()) or best(spark, d))


def heads(spark: SparkSession, d: str, n: int = 64, m: int = 32) -> DataFrame:
    """`head_segment` of all documents, kept; only the words that segments are made of are split off."""
    first = table(spark, d, "documents").select("doc_id", F.explode(F.array(first_tokens("text", n + m))).alias("tk"))  # split once, not again for each use
    return shared(("heads", d, n, m), spark, lambda: segments.head_segment(first, n, m))


def probes(spark: SparkSession, d: str, n: int = 64, m: int = 32) -> DataFrame:
    return shared(("probe", d, n, m), spark, lambda: memorize.probe(heads(spark, d, n, m), greedy_table(spark, d), m))


def kept(d: DataFrame) -> int:
    """1.6 % of the probed documents, 40 at least."""
    return max(40, round(0.016 * d.count()))


def chosen(spark: SparkSession, d: str) -> DataFrame:
    """The segments that tuning uses: best recited ones of seen documents."""

    def make():
        known = cut(sampling.seen(probes(spark, d)))
        return memorize.top_segments(known, kept(known))

    return shared(("top", d), spark, make)


def pair_rows(spark: SparkSession, d: str) -> DataFrame:
    """The chosen segments and their twins. Only the words before a changed one are counted for them, not all contexts."""

    def twin(segs: DataFrame) -> DataFrame:
        return paraphrase.substitute(segs, lm.after(seen(spark, d).select("tk"), paraphrase.asked(segs)))

    return shared(("pairs", d), spark, lambda: paraphrase.rewrite(chosen(spark, d), twin))


def _task(key: str):
    return F.element_at(F.array(F.lit("story"), F.lit("poem"), F.lit("speech")), (hash32("task", key) % 3 + 1).cast("int"))


def turns(spark: SparkSession, d: str) -> DataFrame:
    """Recorded outputs: assistant turns, their conversation dealt over three tasks."""
    c = table(spark, d, "conversations").where("role = 'assistant'")
    return c.select(F.concat_ws("-", "conv_id", "turn").alias("output_id"), _task("conv_id").alias("task"), "text", tokens("text").alias("tk"))


def outputs(spark: SparkSession, d: str) -> DataFrame:
    """Recorded outputs, and what the model writes after the heads of all documents."""
    own = probes(spark, d).select(F.col("seg_id").alias("output_id"), _task("doc_id").alias("task"), F.col("generated").alias("tk"))
    return turns(spark, d).select("output_id", "task", "tk").unionByName(own)


def ratios(spark: SparkSession, d: str) -> DataFrame:
    return shared(("ratios", d), spark, lambda: untargeted.overlap_range(outputs(spark, d), seen(spark, d)))


# --- sampling and segments


@query("sample_docs", f"SELECT doc_id FROM (SELECT doc_id, {S.h32('sample', 'doc_id')} AS h FROM documents ORDER BY h, doc_id LIMIT 100)")
def sample_docs(spark, d):
    return sampling.sample_docs(table(spark, d, "documents").select("doc_id"), 100)


@query("sample_fraction", f"SELECT doc_id FROM documents WHERE {S.h32('sample', 'doc_id')} / 4294967296.0 < 0.1")
def sample_fraction(spark, d):
    return sampling.sample_fraction(table(spark, d, "documents").select("doc_id"), 0.1)


_SEG = "SELECT seg_id, doc_id, array_to_string(prefix, ' ') AS prefix, array_to_string(reference, ' ') AS reference FROM "


def _seg(df):
    return df.select("seg_id", "doc_id", F.array_join("prefix", " ").alias("prefix"), F.array_join("reference", " ").alias("reference"))


@query("segments_64_32", f"WITH {S.TOK}, {S.heads('s', 64, 32)} {_SEG} s")
def segments_64_32(spark, d):
    return _seg(segments.head_segment(docs(spark, d)))


@query("segments_200_50", f"WITH {S.TOK}, {S.heads('s', 200, 50)} {_SEG} s")
def segments_200_50(spark, d):
    return _seg(segments.head_segment(docs(spark, d), 200, 50))


@query("segments_stride", f"WITH {S.TOK}, s AS (SELECT doc_id || '-' || a AS seg_id, doc_id, tk[a + 1:a + 64] AS prefix, tk[a + 65:a + 96] AS reference FROM (SELECT doc_id, tk, unnest(range(0, len(tk) - 95, 96)) AS a FROM tok WHERE len(tk) >= 96)) {_SEG} s")
def segments_stride(spark, d):
    return _seg(segments.stride_segments(docs(spark, d), 64, 32, 96))


_HELD = f"""WITH {S.TOK}, s AS (SELECT *, {S.h32('split', 'doc_id')} % 2 = 0 AS sn FROM tok),
g AS (SELECT DISTINCT unnest({S.gram('tk', 11)}) AS g FROM s WHERE sn),
m AS (SELECT DISTINCT doc_id FROM (SELECT doc_id, unnest({S.gram('tk', 11)}) AS g FROM s WHERE NOT sn) JOIN g USING (g))
SELECT doc_id, text NOT IN (SELECT text FROM s WHERE sn) AS text_guard, text NOT IN (SELECT text FROM s WHERE sn) AND doc_id NOT IN (SELECT doc_id FROM m) AS gram_guard FROM s WHERE NOT sn"""


@query("holdout_split", _HELD)
def holdout_split(spark, d):
    """Held-out documents, and which survive the guard by text and the guard by 11-gram."""
    x = docs(spark, d)
    a = sampling.held(x, "text").select("doc_id", F.lit(True).alias("_t"))
    b = sampling.held(x, "grams").select("doc_id", F.lit(True).alias("_g"))
    out = sampling.held(x).select("doc_id").join(a, "doc_id", "left").join(b, "doc_id", "left")
    return out.select("doc_id", F.coalesce("_t", F.lit(False)).alias("text_guard"), F.coalesce("_g", F.lit(False)).alias("gram_guard"))


# --- language model, decoding, probing


@query("ngram_counts", f"WITH {S.NG} SELECT ord, {S.h32('b', 'ctx')} % 16 AS bucket, count(*) AS n_rows, sum(cnt)::BIGINT AS total, max(cnt) AS most FROM ng GROUP BY ALL")
def ngram_counts(spark, d):
    """The count table, summed up by order and context bucket."""
    return counts(spark, d).groupBy("ord", (hash32("b", "ctx") % 16).alias("bucket")).agg(F.count(F.lit(1)).alias("n_rows"), F.sum("cnt").alias("total"), F.max("cnt").alias("most"))


@query("best_next", f"WITH {S.BEST} SELECT b.ord, b.ctx, b.tok, b.cnt, t.total, t.n_next FROM best b JOIN tot t ON b.ord = t.ord AND b.ctx = t.ctx")
def best_next(spark, d):
    return lm.best_next(counts(spark, d))


_PROBE = f"WITH RECURSIVE {S.BEST}, {S.heads('segs', 64, 32)}, {S.decoded('dec', 'segs', 32)}, ab AS (SELECT s.seg_id AS id, generated AS a, reference AS b FROM segs s JOIN dec USING (seg_id)), {S.lcs('l', 'ab')}, probe AS MATERIALIZED (SELECT s.seg_id, s.doc_id, s.source, s.reference, s.prefix, d.generated, lcs, lcs / 32 AS rouge_l FROM segs s JOIN dec d USING (seg_id) JOIN l ON l.id = s.seg_id)"


@query("decode_greedy", _PROBE + " SELECT seg_id, array_to_string(generated, ' ') AS generated FROM probe")
def decode_greedy(spark, d):
    return probes(spark, d).select("seg_id", F.array_join("generated", " ").alias("generated"))


def _decoded(spark, d, table, strategy: str):
    segs = heads(spark, d).select(F.col("seg_id").alias("id"), F.col("prefix").alias("given"))
    out = decode.greedy(segs, table, 32, strategy=strategy)
    return out.select(F.col("id").alias("seg_id"), F.array_join("generated", " ").alias("generated"))


_GENERATED = _PROBE + " SELECT seg_id, array_to_string(generated, ' ') AS generated FROM probe"


@query("decode_greedy_frontier", _GENERATED)
def decode_greedy_frontier(spark, d):
    """By the strategy for tables that can't be broadcast."""
    return _decoded(spark, d, greedy_table(spark, d), "frontier")


@query("decode_greedy_doubling", _GENERATED)
def decode_greedy_doubling(spark, d):
    """By jumps over the automaton of all contexts, five joins for 32 tokens."""
    return _decoded(spark, d, lm.best_next(counts(spark, d)), "doubling")


@query("decode_greedy_recursive", _GENERATED)
def decode_greedy_recursive(spark, d):
    """By one recursive SQL statement."""
    return _decoded(spark, d, greedy_table(spark, d), "recursive")


@query("probe_greedy", _PROBE + " SELECT seg_id, doc_id, lcs, round(rouge_l, 6)::DOUBLE AS rouge_l FROM probe")
def probe_greedy(spark, d):
    return probes(spark, d).select("seg_id", "doc_id", "lcs", F.round("rouge_l", 6).alias("rouge_l"))


_TOPK = f", sprobe AS (SELECT * FROM probe WHERE {S.h32('split', 'doc_id')} % 2 = 0), top AS MATERIALIZED (SELECT * FROM sprobe ORDER BY rouge_l DESC, seg_id LIMIT (SELECT greatest(40, round(0.016 * count(*)))::BIGINT FROM sprobe))"


@query("memorized_topk", _PROBE + _TOPK + " SELECT seg_id, lcs FROM top")
def memorized_topk(spark, d):
    return chosen(spark, d).select("seg_id", "lcs")


@query("memorized_threshold", _PROBE + " SELECT seg_id, lcs FROM probe WHERE rouge_l >= 0.9")
def memorized_threshold(spark, d):
    return memorize.above(probes(spark, d)).select("seg_id", "lcs")


@query("memorized_topk_by_model", _PROBE + " SELECT source AS model, seg_id, lcs FROM probe QUALIFY row_number() OVER (PARTITION BY source ORDER BY rouge_l DESC, seg_id) <= 3")
def memorized_topk_by_model(spark, d):
    """Each model its own k; the source stands for the model that a probe was made with."""
    p = probes(spark, d).join(table(spark, d, "documents").select("doc_id", F.col("source").alias("model")), "doc_id")
    return memorize.top_segments(p, 3, by="model").select("model", "seg_id", "lcs")


@query("random_segments", f"WITH {S.TOK}, {S.heads('s', 64, 32)} SELECT seg_id FROM s ORDER BY {S.h32('random', 'seg_id')}, seg_id LIMIT 40")
def random_segments(spark, d):
    return memorize.random_segments(segments.head_segment(docs(spark, d)), 40).select("seg_id")


_NUC = f"""WITH {S.NG}, w AS (SELECT *, pow(cnt::DOUBLE, 1 / 0.7) AS w FROM ng),
p AS (SELECT *, w / sum(w) OVER (PARTITION BY ord, ctx) AS p FROM w),
q AS (SELECT *, coalesce(sum(p) OVER (PARTITION BY ord, ctx ORDER BY cnt DESC, tok ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS bf FROM p)
SELECT ord, ctx, count(*) AS n_kept, round(sum(p), 6) AS mass, min(tok) AS least_tok FROM q WHERE round(bf, 9) < 0.9 GROUP BY ord, ctx"""


def nuclei(spark, d):
    return shared(("nucleus", d), spark, lambda: lm.nucleus_table(counts(spark, d)))


def drawn(spark, d):
    """The nuclei that decoding looks up, made of the counts of one part of the contexts after another, without those that a shorter context repeats."""
    n = parts(spark, d)

    def part(k: int):
        plain = keep(lm.fit(seen(spark, d).select("tk"), part=(k, n)))
        nuclei = keep(lm.nucleus_table(plain))
        drop(plain)
        return lm.without_repeats(nuclei), lambda: drop(nuclei)

    return remember(("drawn", d), spark, lambda: keep_parts(spark, n, part))


def nucleus_table(spark: SparkSession, d: str) -> packed.Packed | DataFrame:
    """`drawn` in whole numbers; as rows where the words are too many bytes to travel."""
    return remember(("drawn table", d), spark, lambda: packed.make(seen(spark, d).select("text"), packed.Nucleus(0.7, 0.9)) or drawn(spark, d))


@query("nucleus_set", _NUC)
def nucleus_set(spark, d):
    """The nucleus after each context at T = 0.7 and top-p = 0.9."""
    return nuclei(spark, d).select("ord", "ctx", F.size("toks").cast("long").alias("n_kept"), F.round("mass", 6).alias("mass"), F.array_min("toks").alias("least_tok"))


@query("decode_nucleus")
def decode_nucleus(spark, d):
    """32 sampled tokens after the first user turn of each conversation."""
    first = table(spark, d, "conversations").where("role = 'user'").groupBy("conv_id").agg(F.min_by("text", "turn").alias("text"))
    given = first.select(F.col("conv_id").cast("string").alias("id"), tokens("text").alias("given"))
    return decode.nucleus(given, nucleus_table(spark, d), 32).select("id", F.array_join("generated", " ").alias("generated"))


_NLLSRC = "src AS (SELECT seg_id AS id, prefix AS given, reference AS txt FROM segs)"


@query("sequence_nll", f"WITH {S.NG}, {S.heads('segs', 64, 32)}, {_NLLSRC}, {S.nll('x', 'src')} SELECT id AS seg_id, n_tokens, round(nll, 6) AS nll FROM x")
def sequence_nll(spark, d):
    told = remember(("nll", d), spark, lambda: likelihoods(spark, d, segments.head_segment(docs(spark, d)), "seg_id", "prefix", "reference", [lm.MIX]))
    return told.select("seg_id", "n_tokens", F.round("nll0", 6).alias("nll"))


# --- pairs

_SUCC = """, su AS (SELECT ctx, tok, cnt, row_number() OVER (PARTITION BY ctx ORDER BY cnt DESC, tok) AS r FROM ng WHERE ord = 1 QUALIFY r <= 16),
so AS MATERIALIZED (SELECT ctx, list(tok ORDER BY r) AS options FROM su GROUP BY ctx)"""


def _pairs_sql() -> str:
    pick = S.h32("rewrite", "seg_id || ':' || pos")
    return (
        _PROBE + _TOPK + _SUCC + f""",
w AS (SELECT seg_id, doc_id, prefix, reference, unnest(reference) AS tok, unnest(range(len(reference))) AS pos FROM top),
w2 AS (SELECT w.*, CASE WHEN pos > 0 THEN list_filter(options, lambda x: x <> w.tok) END AS other FROM w LEFT JOIN so ON pos > 0 AND so.ctx = w.reference[pos]),
w3 AS (SELECT seg_id, list(CASE WHEN pos % 3 = 1 AND len(other) > 0 THEN other[({pick} % len(other) + 1)::BIGINT] ELSE tok END ORDER BY pos) AS rewrite FROM w2 GROUP BY seg_id),
pr AS MATERIALIZED (SELECT t.seg_id AS pair_id, t.doc_id, t.prefix AS prompt, t.reference AS original, rewrite FROM top t JOIN w3 USING (seg_id) WHERE rewrite <> t.reference)"""
    )


_PAIRS = _pairs_sql()
_J = lambda c: f"array_to_string({c}, ' ') AS {c}"


@query("paraphrase_pairs", _PAIRS + f" SELECT pair_id, {_J('original')}, {_J('rewrite')} FROM pr")
def paraphrase_pairs(spark, d):
    return pair_rows(spark, d).select("pair_id", F.array_join("original", " ").alias("original"), F.array_join("rewrite", " ").alias("rewrite"))


@query("pair_quality", _PAIRS + f""", ab2 AS (SELECT pair_id AS id, rewrite AS a, original AS b FROM pr), {S.lcs('l2', 'ab2')},
c1 AS (SELECT pair_id, tok, sum(a)::DOUBLE AS a, sum(b)::DOUBLE AS b FROM (SELECT pair_id, unnest(original) AS tok, 1 AS a, 0 AS b FROM pr UNION ALL SELECT pair_id, unnest(rewrite), 0, 1 FROM pr) GROUP BY ALL),
c2 AS (SELECT pair_id, sum(a * b) / (sqrt(sum(a * a)) * sqrt(sum(b * b))) AS cosine FROM c1 GROUP BY 1)
SELECT pair_id, round(lcs / len(original), 6)::DOUBLE AS overlap, round(cosine, 6) AS cosine, lcs / len(original) <= 0.9 AND cosine >= 0.3 AS ok FROM pr JOIN l2 ON id = pair_id JOIN c2 USING (pair_id)""")
def pair_quality(spark, d):
    return paraphrase.gate(pair_rows(spark, d)).select("pair_id", F.round("overlap", 6).alias("overlap"), F.round("cosine", 6).alias("cosine"), "ok")


def _pref(df):
    return df.select("pair_id", "directive", "origin", F.array_join("chosen", " ").alias("chosen"), F.array_join("rejected", " ").alias("rejected"))


@query("prefs_default", _PAIRS + " SELECT pair_id, NULL::VARCHAR AS directive, 'rewrite' AS origin, array_to_string(rewrite, ' ') AS chosen, array_to_string(original, ' ') AS rejected FROM pr")
def prefs_default(spark, d):
    return _pref(pairs.to_preferences(pair_rows(spark, d)))


_DIR = "SELECT pair_id, directive, 'rewrite' AS origin, array_to_string(CASE WHEN ok THEN original ELSE rewrite END, ' ') AS chosen, array_to_string(CASE WHEN ok THEN rewrite ELSE original END, ' ') AS rejected FROM "


@query("prefs_directive", _PAIRS + f" {_DIR} (SELECT *, {S.h32('directive', 'pair_id')} % 1000 < 500 AS ok, CASE WHEN ok THEN '{pairs.ALLOW}' ELSE '{pairs.FORBID}' END AS directive FROM pr)")
def prefs_directive(spark, d):
    return _pref(pairs.with_directives(pair_rows(spark, d)))


CATALOG = ((0, "quote freely", True), (1, "use your own words", False), (2, "exact wording is fine", True), (3, "do not repeat sources", False))


@query("prefs_directive_catalog", _PAIRS + f", cat AS (SELECT * FROM (VALUES {', '.join(str((a, b, c)) for a, b, c in CATALOG)}) AS v(slot, directive, ok)) {_DIR} (SELECT pr.*, cat.ok, cat.directive FROM pr JOIN cat ON slot = {S.h32('directive', 'pair_id')} % 4)")
def prefs_directive_catalog(spark, d):
    return _pref(pairs.with_catalog(pair_rows(spark, d), spark.createDataFrame(list(CATALOG), "slot int, directive string, allow boolean")))


_GEN = f"""gt AS (SELECT conv_id, turn, role, {S.toks('text')} AS tk, lead(role) OVER w AS r2, lead({S.toks('text')}) OVER w AS answer FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
ga AS (SELECT * FROM gt WHERE role = 'user' AND r2 = 'assistant'),
go AS (SELECT conv_id, arg_min(answer, turn) AS a, {S.h32('ring', 'conv_id')} AS h FROM ga GROUP BY conv_id),
gn AS (SELECT greatest(1, count(*) // 1000) AS n FROM go),
gr AS (SELECT conv_id, coalesce(lead(a) OVER x, first_value(a) OVER x) AS other FROM go, gn WINDOW x AS (PARTITION BY h % n ORDER BY h, conv_id)),
gp AS MATERIALIZED (SELECT 'g-' || ga.conv_id || '-' || turn AS pair_id, tk AS prompt, answer AS chosen, other AS rejected FROM ga JOIN gr USING (conv_id) WHERE answer <> other)"""


@query("generic_prefs", f"WITH {_GEN} SELECT pair_id, NULL::VARCHAR AS directive, 'generic' AS origin, {_J('chosen')}, {_J('rejected')} FROM gp")
def generic_prefs(spark, d):
    return _pref(pairs.generic(table(spark, d, "conversations")))


@query("prefs_mix", _PAIRS + f""", {_GEN} SELECT pair_id, 'rewrite' AS origin FROM pr UNION ALL
SELECT pair_id, 'generic' FROM (SELECT pair_id FROM gp ORDER BY {S.h32('mix', 'pair_id')}, pair_id LIMIT (SELECT round(count(*) * 0.1 / 0.9)::BIGINT FROM pr))""")
def prefs_mix(spark, d):
    return pairs.mix(pairs.to_preferences(pair_rows(spark, d)), pairs.generic(table(spark, d, "conversations"))).select("pair_id", "origin")


# --- objective on recorded scores

#: A second weighting of the orders, which leans less on long contexts: the tuned model of the likelihood queries.
AFTER = (0.3, 0.4, 0.2, 0.1)


def pair_scores(spark, d):
    """(pair_id, side, logp, logp_ref): both sides of each pair under the re-weighted and the plain model."""

    def make():
        p = pair_rows(spark, d)
        rows = p.select("pair_id", F.lit("chosen").alias("side"), "prompt", F.col("rewrite").alias("text")).unionByName(p.select("pair_id", F.lit("rejected").alias("side"), "prompt", F.col("original").alias("text")))
        rows = rows.withColumn("id", F.concat_ws("/", "pair_id", "side"))
        now = lm.sequence_nll(rows, counts(spark, d), "id", "prompt", "text", AFTER).select("id", (-F.col("nll")).alias("logp"))
        ref = lm.sequence_nll(rows, counts(spark, d), "id", "prompt", "text").select("id", (-F.col("nll")).alias("logp_ref"))
        return rows.select("id", "pair_id", "side").join(now, "id").join(ref, "id")

    return shared(("scores", d), spark, make)


_LOSS = _PAIRS + f""", s2 AS (SELECT pair_id || '/chosen' AS id, prompt AS given, rewrite AS txt FROM pr UNION ALL SELECT pair_id || '/rejected', prompt, original FROM pr),
{S.nll('na', 's2', AFTER)}, {S.nll('nb', 's2')},
z AS (SELECT split_part(na.id, '/', 1) AS pair_id, split_part(na.id, '/', 2) AS side, nb.nll - na.nll AS ratio FROM na JOIN nb USING (id)),
mm AS (SELECT pair_id, max(ratio) FILTER (side = 'chosen') AS c, max(ratio) FILTER (side = 'rejected') AS r, 0.1 * (c - r) AS margin FROM z GROUP BY 1),
ls AS (SELECT *, ln(1 + exp(-abs(margin))) + greatest(-margin, 0) AS loss FROM mm)"""


@query("preference_loss", _LOSS + " SELECT pair_id, round(margin, 6) AS margin, round(loss, 6) AS loss, round(0.1 * c, 6) AS reward_chosen, round(0.1 * r, 6) AS reward_rejected FROM ls")
def preference_loss(spark, d):
    out = objectives.preference_loss(pair_scores(spark, d))
    return out.select("pair_id", *[F.round(c, 6).alias(c) for c in ("margin", "loss", "reward_chosen", "reward_rejected")])


@query("preference_accuracy", _LOSS + " SELECT count(*) AS n, round(avg(loss), 6) AS loss, round(avg(margin), 6) AS margin, round(avg((margin > 0)::INT), 6) AS accuracy FROM ls")
def preference_accuracy(spark, d):
    out = objectives.diagnostics(objectives.preference_loss(pair_scores(spark, d)))
    return out.select("n", *[F.round(c, 6).alias(c) for c in ("loss", "margin", "accuracy")])


# --- targeted measures


def _ab(spark, d):
    return probes(spark, d).select("seg_id", "generated", "reference")


@query("lcs_len", _PROBE + " SELECT seg_id, lcs FROM probe")
def lcs_len(spark, d):
    """Inside Catalyst, without Python."""
    return _ab(spark, d).select("seg_id", rouge.lcs_len("generated", "reference").alias("lcs"))


@query("lcs_len_arrow", _PROBE + " SELECT seg_id, lcs FROM probe")
def lcs_len_arrow(spark, d):
    return _ab(spark, d).select("seg_id", rouge.lcs_len_arrow("generated", "reference").alias("lcs"))


@query("rouge_l", _PROBE + " SELECT seg_id, round(rouge_l, 6)::DOUBLE AS rouge_l FROM probe")
def rouge_l(spark, d):
    return _ab(spark, d).select("seg_id", F.round(rouge.recall(rouge.lcs_len_arrow("generated", "reference"), "reference"), 6).alias("rouge_l"))


@query("rouge_l_prf", _PROBE + " SELECT seg_id, round(lcs / 32, 6)::DOUBLE AS p, round(lcs / 32, 6)::DOUBLE AS r, round(lcs / 32, 6)::DOUBLE AS f FROM probe")
def rouge_l_prf(spark, d):
    x = _ab(spark, d).withColumn("l", rouge.lcs_len_arrow("generated", "reference"))
    p, r, f = rouge.prf(F.col("l"), "generated", "reference")
    return x.select("seg_id", F.round(p, 6).alias("p"), F.round(r, 6).alias("r"), F.round(f, 6).alias("f"))


def web_items(spark, d):
    """Pages as extraction items: 64 words of the text, then 32."""
    p = table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), tokens(page_text()).alias("tk"))
    return segments.head_segment(p)


PAGE = r"""pg AS MATERIALIZED (SELECT page_id, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title, trim(regexp_replace(replace(replace(replace(replace(replace(replace(
  regexp_replace(regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<script[^>]*>.*?</script>', ' ', 'g'), '(?is)<style[^>]*>.*?</style>', ' ', 'g'), '(?is)<nav[^>]*>.*?</nav>', ' ', 'g'), '(?s)<!--.*?-->', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g'),
  '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', ''''), '&nbsp;', ' '), '&amp;', '&'), '\s+', ' ', 'g')) AS body FROM pages)"""


def _extract(src: str, n: int, m: int) -> str:
    return f"{S.heads('ex', n, m, src)}, {S.decoded('xd', 'ex', m)}, xab AS (SELECT seg_id AS id, generated AS a, reference AS b FROM ex JOIN xd USING (seg_id)), {S.lcs('xl', 'xab')} SELECT count(*) AS n, round(avg(CASE WHEN lcs / {m} > 0.5 THEN 100.0::DOUBLE ELSE 0 END), 6) AS extraction, round(avg(lcs / {m}), 6) AS mean_rouge_l FROM xl"


@query("extraction_web", f"WITH RECURSIVE {S.BEST}, {PAGE}, pt AS (SELECT page_id AS doc_id, '' AS source, {S.toks('body')} AS tk FROM pg), {_extract('pt', 64, 32)}")
def extraction_web(spark, d):
    return memorize.extraction_ratio(memorize.probe(keep(web_items(spark, d)), greedy_table(spark, d), 32))


@query("extraction_book", f"WITH RECURSIVE {S.BEST}, {_extract('tok', 200, 50)}")
def extraction_book(spark, d):
    return memorize.extraction_ratio(probes(spark, d, 200, 50))


@query("extraction_report", _PROBE + f" SELECT CASE WHEN {S.h32('split', 'doc_id')} % 2 = 0 THEN 'seen' ELSE 'held' END AS part, count(*) AS n, round(avg(CASE WHEN rouge_l > 0.5 THEN 100.0::DOUBLE ELSE 0 END), 6) AS extraction, round(avg(rouge_l), 6) AS mean_rouge_l FROM probe GROUP BY 1")
def extraction_report(spark, d):
    """The flagship: what the model recites of documents that it saw and of documents that it did not."""
    return memorize.extraction_ratio(sampling.split(probes(spark, d)), 0.5, "part")


@query("extraction_curve", _PROBE + " SELECT k / 10 AS tau, count(*) AS n, round(avg(CASE WHEN rouge_l > k / 10 THEN 100.0::DOUBLE ELSE 0 END), 6) AS extraction FROM probe, range(11) AS r(k) GROUP BY k")
def extraction_curve(spark, d):
    return memorize.extraction_curve(probes(spark, d))


# --- untargeted measures


def _all_hits() -> str:
    return ", ".join(S.hits(f"h{n}", "outs", "seen", n) for n in range(5, 12))


_RAT = f"WITH RECURSIVE {S.BEST}, {S.OUT}, {_all_hits()}, rat AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT output_id, task, {n} AS n, count(*) AS positions, sum(hit::INT)::BIGINT AS matched, sum(hit::INT) / count(*) AS ratio FROM h{n} GROUP BY ALL" for n in range(5, 12)) + ")"


@query("overlap_n", _RAT + " SELECT output_id, task, n, positions, matched, round(ratio, 6)::DOUBLE AS ratio FROM rat")
def overlap_n(spark, d):
    return ratios(spark, d).withColumn("ratio", F.round("ratio", 6))


@query("overlap_scan", f"WITH RECURSIVE {S.BEST}, {S.OUT}, {S.hits('h', 'outs', 'seen', 8)} SELECT output_id, count(*) AS positions, sum(hit::INT)::BIGINT AS matched FROM h GROUP BY 1")
def overlap_scan(spark, d):
    return untargeted.overlap(outputs(spark, d), seen(spark, d), 8).select("output_id", "positions", "matched")


@query("creativity_index", _RAT + " SELECT output_id, task, round(avg(1 - ratio), 6) AS ci, count(*) AS n_lengths FROM rat GROUP BY ALL")
def creativity_index(spark, d):
    return untargeted.creativity_index(ratios(spark, d))


@query("coverage_n", f"""WITH RECURSIVE {S.BEST}, {S.OUT}, {S.hits('h', 'outs', 'seen', 5)}, c AS (SELECT output_id, count(DISTINCT pos + k) AS covered FROM h, range(5) AS r(k) WHERE hit GROUP BY 1)
SELECT o.output_id, len(tk) AS n_tokens, coalesce(covered, 0) AS covered, round(coalesce(covered, 0) / len(tk), 6) AS share FROM outs o LEFT JOIN c USING (output_id) WHERE len(tk) >= 5""")
def coverage_n(spark, d):
    return untargeted.coverage(outputs(spark, d), seen(spark, d), 5).select("output_id", F.col("n_tokens").cast("long").alias("n_tokens"), "covered", "share")


@query("untargeted_report", _RAT + """, t AS (SELECT task, count(*) AS outputs, 100 * avg(ratio) AS score, 100 * sum(matched) / sum(positions) AS micro FROM rat WHERE n = 11 GROUP BY task)
SELECT task, outputs::BIGINT AS outputs, round(score, 6) AS score, round(micro, 6)::DOUBLE AS micro FROM t UNION ALL SELECT NULL, sum(outputs)::BIGINT, round(avg(score), 6), round(avg(micro), 6) FROM t""")
def untargeted_report(spark, d):
    return untargeted.score(ratios(spark, d))


@query("longest_run", f"""WITH RECURSIVE {S.BEST}, {S.OUT}, {S.hits('h', 'outs', 'seen', 5)}, i AS (SELECT output_id, pos, pos - row_number() OVER (PARTITION BY output_id ORDER BY pos) AS isl FROM h WHERE hit),
g AS (SELECT output_id, min(pos) AS start, count(*) + 4 AS tokens FROM i GROUP BY output_id, isl)
SELECT output_id, start::INT AS start, tokens FROM g QUALIFY row_number() OVER (PARTITION BY output_id ORDER BY tokens DESC, start) = 1""")
def longest_run(spark, d):
    return untargeted.longest_run(outputs(spark, d), seen(spark, d))


@query("creativity_recorded", _RAT + """, e AS (SELECT task, output_id, avg(1 - ratio) AS ci, max(ratio) FILTER (n = 5) AS s, max(ratio) FILTER (n = 11) AS l FROM rat GROUP BY ALL)
SELECT task, count(*) AS outputs, round(avg(ci), 6)::DOUBLE AS ci, round(100 * avg(s), 6)::DOUBLE AS short, round(100 * avg(l), 6)::DOUBLE AS long FROM e GROUP BY task""")
def creativity_recorded(spark, d):
    """Index, 5-gram and 11-gram overlap by task of the recorded and the untuned model's outputs."""
    return untargeted.creativity_table(ratios(spark, d))


@query("ci_decomposition", _RAT + """, b AS (SELECT n, avg(ratio) AS v FROM rat WHERE task = 'story' GROUP BY 1), a AS (SELECT n, avg(ratio) AS v FROM rat WHERE task = 'poem' GROUP BY 1)
SELECT n, round(b.v, 6) AS before, round(a.v, 6) AS after, round(a.v - b.v, 6) AS change, round(CASE WHEN sum(a.v - b.v) OVER () <> 0 THEN (a.v - b.v) / sum(a.v - b.v) OVER () END, 6) AS share FROM a JOIN b USING (n)""")
def ci_decomposition(spark, d):
    """Stories against poems: the arithmetic of the decomposition. `creativity_change` has models before and after tuning."""
    r = ratios(spark, d)
    return untargeted.decomposition(r.where("task = 'story'"), r.where("task = 'poem'"))


# --- quotation, utility, likelihood


@query("quotation_recall", f"""WITH RECURSIVE {PAGE}, p AS (SELECT page_id, title, {S.toks('body')}[1:50] AS words FROM pg),
o AS (SELECT a.page_id AS id, a.words AS b, coalesce(arg_min(b.words, b.page_id), []::VARCHAR[]) AS a FROM p a LEFT JOIN p b ON a.title = b.title AND a.page_id <> b.page_id GROUP BY ALL),
{S.lcs('l', 'o')} SELECT count(*) AS n, round(avg(CASE WHEN lcs / len(b) > 0.5 THEN 100.0::DOUBLE ELSE 0 END), 6) AS recall, round(avg(lcs / len(b)), 6) AS mean_rouge_l FROM l JOIN o USING (id)""")
def quotation_recall(spark, d):
    """Recorded recitals: what another page of the same title opens with, against the page's first 50 words."""
    p = table(spark, d, "pages").select("page_id", page_title().alias("title"), F.slice(tokens(page_text()), 1, 50).alias("reference"))
    o = p.select(F.col("page_id").alias("_o"), "title", F.col("reference").alias("_w"))
    j = p.join(o, "title").where("page_id <> _o").groupBy("page_id").agg(F.min_by("_w", "_o").alias("generated"))
    j = p.join(j, "page_id", "left").withColumn("generated", F.coalesce("generated", F.array().cast("array<string>")))
    return memorize.extraction_ratio(memorize.score(j)).withColumnRenamed("extraction", "recall")


def _cloze_sql() -> str:
    return f"""WITH {S.NG}, it AS (SELECT item_id, {S.toks('text')} AS tk FROM benchmark), c AS (SELECT item_id, tk[1:len(tk) - 4] AS stem, tk[len(tk) - 3:] AS ed, {S.h32('cloze', 'item_id')} AS h FROM it WHERE len(tk) > 8),
c2 AS (SELECT *, h % greatest(1, (SELECT count(*) FROM c) // 1000) AS ring FROM c), c3 AS (SELECT *, row_number() OVER (PARTITION BY ring ORDER BY h, item_id) AS k, count(*) OVER (PARTITION BY ring) AS n FROM c2),
op AS (SELECT a.item_id, opt, a.stem, b.ed AS option FROM c3 a, range(4) AS r(opt) JOIN c3 b ON b.ring = a.ring AND b.k = (a.k - 1 + opt) % a.n + 1 WHERE opt < a.n),
src AS (SELECT item_id || ':' || opt AS id, stem AS given, option AS txt FROM op), {S.nll('x', 'src')},
pk AS (SELECT split_part(id, ':', 1)::BIGINT AS item_id, split_part(id, ':', 2)::INT AS opt, round(nll, 9) AS nll FROM x),
ch AS MATERIALIZED (SELECT item_id, opt AS picked, opt = 0 AS correct FROM pk QUALIFY row_number() OVER (PARTITION BY item_id ORDER BY nll, opt) = 1)"""


@query("utility_choice", _cloze_sql() + " SELECT item_id, picked, correct FROM ch")
def utility_choice(spark, d):
    items = table(spark, d, "benchmark").select("item_id", tokens("text").alias("tk"))
    return utility.choice_accuracy(utility.cloze(items), counts(spark, d))


_NUM = f"""itn AS (SELECT o_orderkey AS item_id, round(sum(l_quantity), 2) AS gold FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1),
an AS (SELECT item_id, gold::DECIMAL(18, 2) AS gold, 'Adding up line by line gives 3 parts, so the total is ' || (gold + CASE WHEN {S.h32('slip', 'item_id')} % 5 = 0 THEN 1 ELSE 0 END)::BIGINT || '.' AS answer FROM itn),
nu AS MATERIALIZED (SELECT item_id, gold, regexp_extract_all(replace(answer, ',', ''), '-?[0-9]+(?:\\.[0-9]+)?')[-1]::DECIMAL(18, 2) AS got FROM an)"""


def numeric(spark, d):
    """Order totals with recorded answers, one in five of which slips by one."""
    o = table(spark, d, "orders").select("o_orderkey")
    t = o.join(table(spark, d, "lineitem").select("l_orderkey", "l_quantity"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_orderkey").alias("item_id")).agg(F.round(F.sum("l_quantity"), 2).alias("gold"))
    slip = F.when(hash32("slip", "item_id") % 5 == 0, 1).otherwise(0)
    t = t.withColumn("answer", F.concat(F.lit("Adding up line by line gives 3 parts, so the total is "), (F.col("gold") + slip).cast("long"), F.lit(".")))
    return t.select("item_id", F.col("gold").cast("decimal(18,2)").alias("gold"), utility.last_number("answer").alias("got"))


@query("utility_numeric", f"WITH {_NUM} SELECT count(*) AS n, round(avg((got = gold)::INT), 6) AS accuracy FROM nu")
def utility_numeric(spark, d):
    return numeric(spark, d).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("got") == F.col("gold")).cast("int")), 6).alias("accuracy"))


_EX = f"""sh AS (SELECT n_nationkey AS item_id, r_name AS gold, CASE WHEN {S.h32('short', 'n_nationkey')} % 4 = 0 THEN 'unknown' ELSE '  ' || lower(r_name) || '.' END AS answer FROM nation JOIN region ON n_regionkey = r_regionkey),
xm AS MATERIALIZED (SELECT item_id, trim(regexp_replace(regexp_replace(lower(answer), '[^a-z0-9 ]', ' ', 'g'), ' +', ' ', 'g')) = trim(regexp_replace(regexp_replace(lower(gold), '[^a-z0-9 ]', ' ', 'g'), ' +', ' ', 'g')) AS ok FROM sh)"""


def short_answers(spark, d):
    n = table(spark, d, "nation").join(table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    said = F.when(hash32("short", "n_nationkey") % 4 == 0, "unknown").otherwise(F.concat(F.lit("  "), F.lower("r_name"), F.lit(".")))
    n = n.select(F.col("n_nationkey").alias("item_id"), F.col("r_name").alias("gold"), said.alias("answer"))
    return n.select("item_id", (utility.normal("answer") == utility.normal("gold")).alias("ok"))


@query("utility_exact", f"WITH {_EX} SELECT item_id, ok FROM xm")
def utility_exact(spark, d):
    return short_answers(spark, d)


@query("utility_composite", _cloze_sql() + f", {_NUM}, {_EX}, v AS (SELECT 'knowledge' AS measure, 100 * avg(correct::INT) AS value FROM ch UNION ALL SELECT 'math', 100 * avg((got = gold)::INT) FROM nu UNION ALL SELECT 'reasoning', 100 * avg(ok::INT) FROM xm) SELECT measure, round(value, 6) AS value FROM v UNION ALL SELECT 'composite', round(avg(value), 6) FROM v")
def utility_composite(spark, d):
    mean = lambda df, c, name: df.agg(F.lit(name).alias("measure"), (100 * F.avg(c.cast("int"))).alias("value"))
    v = mean(utility_choice(spark, d), F.col("correct"), "knowledge").unionByName(mean(numeric(spark, d), F.col("got") == F.col("gold"), "math")).unionByName(mean(short_answers(spark, d), F.col("ok"), "reasoning"))
    return v.unionByName(v.agg(F.lit("composite").alias("measure"), F.avg("value").alias("value"))).withColumn("value", F.round("value", 6))


@query("utility_constraints", f"WITH {S.TURNS} SELECT output_id, [len(tk) >= 50, NOT contains(text, '!'), ends_with(trim(text), '.'), len(list_distinct(tk)) * 2 >= len(tk)] AS passed, NOT list_contains(passed, false) AS ok FROM turns")
def utility_constraints(spark, d):
    return utility.constraints(turns(spark, d))


_DUEL = f"""q AS (SELECT doc_id, max(quality) AS quality FROM labels GROUP BY 1), e AS (SELECT doc_id, quality, n_chars, {S.h32('duel', 'doc_id')} AS h FROM q JOIN documents USING (doc_id)),
k AS (SELECT *, row_number() OVER (PARTITION BY h % 16 ORDER BY h, doc_id) - 1 AS r, h % 16 AS b FROM e),
du AS (SELECT a.doc_id AS a_id, b.doc_id AS b_id, CASE WHEN a.quality > b.quality THEN 1.0::DOUBLE WHEN a.quality = b.quality THEN 0.5 ELSE 0 END AS win, ln(1 + a.n_chars) - ln(1 + b.n_chars) AS gap FROM k a JOIN k b ON a.b = b.b AND a.r % 2 = 0 AND b.r = a.r + 1)"""


def duels(spark, d):
    """Labelled documents paired by hash; the judge prefers the better label, ties count half."""
    q = table(spark, d, "labels").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    e = q.join(table(spark, d, "documents").select("doc_id", "n_chars"), "doc_id").withColumn("_h", hash32("duel", "doc_id")).withColumn("_b", F.col("_h") % 16)
    at = Window.partitionBy("_b").orderBy("_h", "doc_id")
    e = e.withColumn("_r", F.row_number().over(at) - 1)
    for c in ("doc_id", "quality", "n_chars"):
        e = e.withColumn(f"_{c}", F.lead(c).over(at))
    e = e.where("_r % 2 = 0 and _doc_id is not null")
    win = F.when(F.col("quality") > F.col("_quality"), 1.0).when(F.col("quality") == F.col("_quality"), 0.5).otherwise(0.0)
    return e.select(F.col("doc_id").alias("a_id"), F.col("_doc_id").alias("b_id"), win.alias("win"), (F.log1p("n_chars") - F.log1p("_n_chars")).alias("gap"))


@query("utility_win_rate", f"WITH {_DUEL} SELECT count(*) AS n, round(100 * avg(win), 6) AS win_rate, round(avg(gap), 6) AS mean_gap FROM du")
def utility_win_rate(spark, d):
    return duels(spark, d).agg(F.count(F.lit(1)).alias("n"), F.round(100 * F.avg("win"), 6).alias("win_rate"), F.round(F.avg("gap"), 6).alias("mean_gap"))


#: Newton steps over the bins, one row a step, the bins in lists.
_NEWTON = f"""WITH RECURSIVE {_DUEL}, bi AS (SELECT round(greatest(-4.0::DOUBLE, least(4.0::DOUBLE, gap)) * 5) / 5 AS g, sum(win) AS w, count(*)::DOUBLE AS n FROM du GROUP BY 1),
li AS MATERIALIZED (SELECT list(g ORDER BY g) AS g, list(w ORDER BY g) AS w, list(n ORDER BY g) AS n FROM bi),
nw AS (SELECT 0 AS step, 0.0::DOUBLE AS a, 0.0::DOUBLE AS b UNION ALL
  SELECT step + 1, a + (hbb * ra - hab * rb) / (haa * hbb - hab * hab), b + (haa * rb - hab * ra) / (haa * hbb - hab * hab) FROM (
    SELECT step, a, b, list_sum(v) + 1e-6 AS haa, list_sum(list_transform(g, lambda x, i: v[i] * x)) AS hab, list_sum(list_transform(g, lambda x, i: v[i] * x * x)) + 1e-6 AS hbb,
      list_sum(list_transform(g, lambda x, i: w[i] - n[i] * p[i])) AS ra, list_sum(list_transform(g, lambda x, i: (w[i] - n[i] * p[i]) * x)) AS rb FROM (
      SELECT *, list_transform(p, lambda q, i: n[i] * q * (1 - q) + 1e-9) AS v FROM (
        SELECT nw.*, li.*, list_transform(g, lambda x: 1 / (1 + exp(-(a + b * x)))) AS p FROM nw, li WHERE step < 50))))
SELECT round(100 / (1 + exp(-a)), 6) AS win_rate FROM nw WHERE step = 50"""


@query("utility_win_rate_controlled", _NEWTON)
def utility_win_rate_controlled(spark, d):
    """The win rate that is left at no length gap."""
    return utility.controlled_win_rate(duels(spark, d)).select(F.round(100 * F.col("win_rate"), 6).alias("win_rate"))


def reweighted(spark, d):
    """Held-out segments under the model and under the same counts with other weights."""

    def make():
        segs = segments.head_segment(sampling.held(docs(spark, d), "text")).withColumnRenamed("seg_id", "id")
        told = likelihoods(spark, d, segs, "id", "prefix", "reference", [lm.MIX, AFTER])
        nll = lambda k: told.select("id", "n_tokens", F.col(f"nll{k}").alias("nll"))
        return utility.nll_shift(nll(0), nll(1))

    return shared(("reweighted", d), spark, make)


_SHIFT = f"WITH {S.NG}, ho AS (SELECT * FROM tok WHERE {S.h32('split', 'doc_id')} % 2 <> 0 AND text NOT IN (SELECT text FROM seen)), {S.heads('segs', 64, 32, 'ho')}, {_NLLSRC}, {S.nll('xb', 'src')}, {S.nll('xa', 'src', AFTER)}, sh AS MATERIALIZED (SELECT id, xb.n_tokens, xb.nll / xb.n_tokens AS before, xa.nll / xa.n_tokens AS after, after - before AS shift FROM xb JOIN xa USING (id))"


@query("nll_reweighted", _SHIFT + " SELECT id, n_tokens, round(before, 6) AS before, round(after, 6) AS after, round(shift, 6) AS shift FROM sh")
def nll_reweighted(spark, d):
    return reweighted(spark, d).select("id", "n_tokens", *[F.round(c, 6).alias(c) for c in ("before", "after", "shift")])


# --- tables of results, over orders and their lines


def _mean(of: str, when: str = "TRUE") -> str:
    return f"sum(({of})::DECIMAL(18, 2)) FILTER ({when})::DOUBLE / nullif(count({of}) FILTER ({when}), 0)"


def _wide(name: str, source: str, model: str, variant: str, columns: str) -> str:
    """name(model, variant, columns): by model and variant, and each model as a whole."""
    return " UNION ALL ".join([f"{name} AS MATERIALIZED (SELECT {model} AS model, {variant} AS variant, {columns} FROM {source} GROUP BY {model}, {variant}", f"SELECT {model}, '{report.WHOLE}', {columns} FROM {source} GROUP BY {model})"])


_PUB = (
    _wide("pb", "orders", "o_orderstatus", "o_orderpriority", f"count(*)::DOUBLE AS items, {_mean('o_totalprice')} AS price, min(o_totalprice) AS least, max(o_totalprice) AS most")
    + ", " + _wide("pi", "lineitem", "l_linestatus", "l_returnflag", f"count(*)::DOUBLE AS items, {_mean('l_extendedprice')} AS price, {_mean('l_quantity')} AS quantity, {_mean('l_discount')} AS discount, {_mean('l_extendedprice', 'l_quantity >= 50')} AS bulk_price")
    + ", " + _wide("pw", "lineitem", "l_linestatus", "l_returnflag", ", ".join(f"count(*) FILTER ({w})::DOUBLE AS {t}_items, {_mean('l_extendedprice', w)} AS {t}_price, {_mean('l_discount', w)} AS {t}_discount" for t, w in report.SIZES.items()))
    + f""", lo AS (SELECT model, variant, metric, value FROM pb UNPIVOT (value FOR metric IN ({', '.join(report.ORDER_METRICS)}))
UNION ALL SELECT model, variant, metric, value FROM (SELECT * FROM pi WHERE NOT EXISTS (SELECT 1 FROM pb WHERE pb.model = pi.model AND pb.variant = pi.variant)) UNPIVOT (value FOR metric IN ({', '.join(report.LINE_METRICS)})))"""
)


def results(spark, d) -> DataFrame:
    return report.long_report(table(spark, d, "orders"), table(spark, d, "lineitem"))


@query("published_report", f"WITH {_PUB} SELECT * FROM lo")
def published_report(spark, d):
    """Two wide tables of results as one long one, each value once."""
    return results(spark, d)


@query("published_writing", f"WITH {_PUB} SELECT model, variant, metric, value FROM pw UNPIVOT (value FOR metric IN ({', '.join(report.SIZE_METRICS)}))")
def published_writing(spark, d):
    """A wide table of tasks (sizes) and measures as a long one."""
    return report.size_report(table(spark, d, "lineitem"))


_CHECKS = f"""WITH {_PUB}, c AS ({' UNION ALL '.join(f"SELECT model, variant, '{m}' AS measure, (small_{m} + medium_{m} + large_{m}) / 3 AS computed FROM pw" for m in ('price', 'discount'))}),
p AS (SELECT model, variant, 'price' AS measure, price AS printed FROM pi UNION ALL SELECT model, variant, 'discount', discount FROM pi)
SELECT model, variant, measure, round(computed, 6) AS computed, printed, abs(round(computed, 6) - printed) < 0.05 AS agrees FROM c JOIN p USING (model, variant, measure)"""


@query("published_checks", _CHECKS)
def published_checks(spark, d):
    """Whether means of the whole follow from the parts' means; some don't."""
    return report.size_checks(table(spark, d, "lineitem"))


@query("relative_reduction", f"WITH {_PUB} SELECT a.model, a.variant, a.metric, a.value, round(CASE WHEN b.value <> 0 THEN 100 * (b.value - a.value) / b.value END, 6) AS reduction FROM lo a JOIN lo b ON a.model = b.model AND a.metric = b.metric AND b.variant = '{report.WHOLE}' WHERE a.variant <> '{report.WHOLE}'")
def relative_reduction(spark, d):
    return report.reduction(results(spark, d), report.WHOLE)


@query("report_pivot", f"WITH {_PUB} SELECT model, metric, max(value) FILTER (variant = '{report.WHOLE}') AS {report.WHOLE}, max(value) FILTER (variant = 'R') AS R FROM lo GROUP BY ALL")
def report_pivot(spark, d):
    return results(spark, d).groupBy("model", "metric").pivot("variant", [report.WHOLE, "R"]).max("value")


@query("tradeoff_pareto", f"WITH {_PUB}, p AS (SELECT model || '/' || variant AS name, max(value) FILTER (metric = 'price') AS utility, max(value) FILTER (metric = 'items') AS copying FROM lo GROUP BY ALL) SELECT * FROM p WHERE NOT EXISTS (SELECT 1 FROM p q WHERE q.utility >= p.utility AND q.copying <= p.copying AND (q.utility > p.utility OR q.copying < p.copying))")
def tradeoff_pareto(spark, d):
    """Mean price against number over all variants."""
    w = results(spark, d).groupBy(F.concat("model", F.lit("/"), "variant").alias("name")).pivot("metric", ["price", "items"]).max("value")
    return report.pareto(w.select("name", F.col("price").alias("utility"), F.col("items").alias("copying")))


@query("examples", f"""WITH RECURSIVE {S.BEST}, {S.OUT}, {S.hits('h', 'outs', 'seen', 5)}, i AS (SELECT output_id, pos, pos - row_number() OVER (PARTITION BY output_id ORDER BY pos) AS isl FROM h WHERE hit),
g AS (SELECT output_id, min(pos) AS start, count(*) + 4 AS tokens FROM i GROUP BY output_id, isl),
b AS (SELECT output_id, max(tokens) AS longest, list(start) AS opens, list(start + tokens - 1) AS closes FROM g GROUP BY 1)
SELECT b.output_id, array_to_string(list_transform(tk, lambda x, k: CASE WHEN list_contains(opens, k - 1) THEN '[' ELSE '' END || x || CASE WHEN list_contains(closes, k - 1) THEN ']' ELSE '' END), ' ') AS marked, longest::BIGINT AS longest
FROM b JOIN outs USING (output_id) ORDER BY longest DESC, output_id LIMIT 5""")
def examples(spark, d):
    """The five outputs with the longest copied stretches, every copied stretch in brackets."""
    outs = cut(outputs(spark, d))
    r = cut(untargeted.runs(outs, seen(spark, d)))
    best = r.groupBy("output_id").agg(F.max("tokens").alias("longest")).orderBy(F.col("longest").desc(), "output_id").limit(5)
    told = r.join(F.broadcast(best), "output_id").groupBy("output_id", "longest").agg(F.collect_list(F.struct("start", "tokens")).alias("_s"))
    return outs.select("output_id", "tk").join(told, "output_id").select("output_id", report.marked("tk", "_s").alias("marked"), "longest")
