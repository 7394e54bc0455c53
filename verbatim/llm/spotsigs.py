"""SpotSigs: document fingerprints from the content words that follow common words.

Every common word is an anchor; the CHAIN content words after it (skipping other anchors)
form a signature with it. The start of a text is an anchor too, and its end fills short
chains, so each text has signatures. A document's fingerprint is its set of signatures;
documents are compared by Jaccard likeness, and only where set lengths allow the threshold.

All of it is DataFrame functions. Anchors are tied to the next content word by one regular
expression and removed by another, which leaves two arrays of equal length; a signature is
made where they differ.

Near duplicates are found by set length and pruned comparison: sets are dealt by length band
and by few of their signatures, so that two sets as alike as asked for must meet, and only
sets that meet are compared whole.

Defined results: null is the empty text; equal texts have equal fingerprints; documents that
share an id follow each other by text hash; null ids come last in descending order, by text
hash; rows equal in id and text are each other's next; a lone document is its own next; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

# Common words of four languages that serve as anchors.
ANCHORS = (
    "the a an and of to in is was are be that this it for on with as by at from not "
    "der die das und ist ein eine den dem des von mit zu auf nicht sich als "
    "le la les de du et est un une que qui pour pas sur par au avec dans "
    "el los las y en por con para del se su al es no lo"
).split()

CHAIN, LIKENESS = 3, 0.8
#: Low bits of an id that don't count for its block, where documents meet the next one; rows beyond which a block is split by id and text hash; equal rows beyond which one stands for all.
BLOCK_BITS, HEAVY, MANY = 8, 4096, 64
#: A signature dealt by more sets than HOT goes to the end of the order; lists of more than LONG sets go through at most ROUNDS rounds while the pairs left are more than PAIRS a member.
HOT, LONG, PAIRS, ROUNDS = 64, 32, 4, 4

START, TIE, END = "\u0004", "\u0001", "\u0003"


def _trie(words: list[str]) -> str:
    """A pattern for any of the words that reads each letter once."""
    heads = sorted({w[0] for w in words if w})
    ways = [h + _trie([w[1:] for w in words if w[:1] == h]) for h in heads]
    if not ways:
        return ""
    return f"(?:{'|'.join(ways)})" + "?" * ("" in words)


_ANY = _trie([START, *ANCHORS])


def with_signatures(df: DataFrame, text: str, out: str, chain: int = CHAIN) -> DataFrame:
    """`df` with `out`: the set of signatures (array<long>, without repeats) of the column `text`."""
    plain = F.trim(F.regexp_replace(F.lower(F.col(text)), r"[^\p{L}\p{N}]+", " "))
    whole = F.concat(F.lit(f" {START} "), plain, F.lit(" " + f"{END} " * chain))
    df = df.withColumn("_whole", whole)
    tied = F.split(F.trim(F.regexp_replace("_whole", f"(?<= )({_ANY}) ", f"$1{TIE}")), " +")
    bare = F.split(F.trim(F.regexp_replace("_whole", f"(?<= )(?:{_ANY}) ", "")), " +")
    df = df.withColumn("_tied", tied).withColumn("_bare", bare)
    after = lambda i: [F.get("_bare", i + k) for k in range(chain)]
    made = F.transform("_tied", lambda x, i: F.when(F.instr(x, TIE) > 0, F.xxhash64(F.substring_index(x, TIE, -2), *after(i))))
    return df.withColumn(out, F.array_distinct(F.array_compact(made))).drop("_whole", "_tied", "_bare")


def fingerprint(signatures: Column) -> Column:
    """64 hex digits that stand for the whole set."""
    return F.sha2(F.array_join(F.sort_array(signatures).cast("array<string>"), ","), 256)


def jaccard(a: Column, b: Column) -> Column:
    both = F.size(F.array_intersect(a, b))
    return both / (F.size(a) + F.size(b) - both)


def with_next(docs: DataFrame, bits: int = BLOCK_BITS, heavy: int = HEAVY, many: int = MANY) -> tuple[DataFrame, Window]:
    """(doc_id, _text, _h, _guest, _k, block columns) dealt by blocks of ids, and the window in which the row after a document is the next one by falling id.

    Each block also gets, as a guest, the first document of the next block that holds any (the
    last block that of the first). Those are picked from ids alone; texts are shuffled once. A
    block with too many rows (ids that repeat, or are null) is split by id and by the first bits
    of the text hash; of very many rows equal in both, one stands for _k.
    """
    block = ["_b", "_b1", "_b2"]
    d = docs.select("doc_id", C.text_or_empty("text").alias("_text"), F.xxhash64("text").alias("_h"), F.coalesce(F.shiftright("doc_id", bits), F.lit(-(1 << 62))).alias("_b"))
    full = C.cut(d.groupBy("_b").agg(F.count(F.lit(1)).alias("_n")).where(F.col("_n") > heavy).select("_b", F.ceil(F.log2(F.col("_n") / (1 << bits))).cast("int").alias("_s")))
    if full.limit(1).count():
        d = d.join(C.maybe_broadcast(full), "_b", "left")
        cuts = F.call_function("shiftright", F.col("_h"), F.lit(64) - F.col("_s"))
        d = d.withColumn("_b1", F.when(F.col("_s").isNotNull(), F.col("doc_id"))).withColumn("_b2", cuts)
        again = C.cut(d.where("_s is not null").groupBy(F.col("doc_id").alias("_id"), F.col("_h").alias("_hh")).agg(F.count(F.lit(1)).alias("_k")).where(F.col("_k") > many))
        keys = F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_h") == F.col("_hh"))
        short = C.maybe_broadcast(again)
        one = d.join(short, keys).groupBy("doc_id", "_h", *block).agg(F.first("_text").alias("_text"), F.first("_k").alias("_k"))
        d = d.join(short, keys, "left_anti").withColumn("_k", F.lit(1).cast("long")).select("doc_id", "_text", "_h", *block, "_k").unionByName(one)
    else:
        d = d.withColumn("_b1", F.lit(None).cast(docs.schema["doc_id"].dataType)).withColumn("_b2", F.lit(None).cast("long")).withColumn("_k", F.lit(1).cast("long"))
    heads = d.groupBy(*block).agg(F.max(F.struct("doc_id", "_h")).alias("_m"))
    heads = C.cut(C.global_index(heads, [F.col("_b").desc(), F.col("_b1").desc_nulls_last(), F.col("_b2").desc_nulls_last()], "_i"))
    n = heads.count()
    guests = heads.select(F.col("_m.doc_id").alias("_id"), F.col("_m._h").alias("_hh"), ((F.col("_i") + n - 1) % F.lit(max(1, n))).alias("_i"))
    guests = C.cut(guests.join(heads.select("_i", *[F.col(c).alias(f"_to{c}") for c in block]), "_i").drop("_i"))
    guests = d.join(C.maybe_broadcast(guests), F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_h") == F.col("_hh")))
    guests = guests.select("doc_id", "_text", "_h", *[F.col(f"_to{c}").alias(c) for c in block], "_k", F.lit(1).alias("_guest"))
    rows = d.withColumn("_guest", F.lit(0)).select("doc_id", "_text", "_h", *block, "_k", "_guest").unionByName(guests)
    return rows, Window.partitionBy(*block).orderBy("_guest", F.col("doc_id").desc_nulls_last(), F.col("_h").desc())


def compare_edited(docs: DataFrame, heavy: int = HEAVY, many: int = MANY) -> DataFrame:
    """Each document against its edited text and the next document (see `op9_spotsigs`)."""
    rows, at = with_next(docs, heavy=heavy, many=many)
    rows = rows.withColumn("_next", F.lead("_text").over(at))
    rows = with_signatures(rows, "_text", "_own").withColumn("_nsig", F.lead("_own").over(at)).where("_guest = 0")
    # one row stands for _k equal ones: the last of them has the next document, each other one has itself
    twin = F.struct(F.col("_text").alias("_next"), F.col("_own").alias("_nsig"), (F.col("_k") - 1).alias("_c"))
    last = F.struct("_next", "_nsig", F.lit(1).cast("long").alias("_c"))
    rows = rows.withColumn("_x", F.explode(F.when(F.col("_k") > 1, F.array(last, twin)).otherwise(F.array(last))))
    rows = rows.select("doc_id", "_text", "_own", "_x._next", "_x._nsig", "_x._c")
    n = F.length("_text")
    half = F.floor(n / 2).cast("int")
    rows = rows.withColumn("_edited", F.concat(F.substring("_text", F.lit(1), n - half), F.substring("_next", F.lit(1), half)))
    rows = with_signatures(rows, "_edited", "_esig")
    out = rows.select("doc_id", n.cast("long").alias("n_chars"), F.sha2("_edited", 256).alias("edited_sha256"), fingerprint(F.col("_own")).alias("fingerprint"), fingerprint(F.col("_esig")).alias("edited_fingerprint"), jaccard(F.col("_own"), F.col("_esig")).alias("near_edited"), jaccard(F.col("_own"), F.col("_nsig")).alias("near_next"), "_c")
    # copies of a result are dealt in hundreds, each hundred anywhere
    some = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("_c") - 1) / 100)))
    each = out.withColumn("_p", some)
    size = F.least(F.lit(100), F.col("_c") - F.col("_p") * 100).cast("int")
    return each.withColumn("_z", F.explode(F.array_repeat(F.lit(1), size))).drop("_c", "_p", "_z")


def _verified(pairs: DataFrame, classes: DataFrame, least: float) -> DataFrame:
    """(a, b, likeness) of the pairs (a, b) whose whole sets are `least` alike."""
    full = classes.select("_c", "_s")
    met = pairs.distinct().join(full.withColumnsRenamed({"_c": "a", "_s": "_sa"}), "a").join(full.withColumnsRenamed({"_c": "b", "_s": "_sb"}), "b")
    return C.cut(met.withColumn("likeness", jaccard(F.col("_sa"), F.col("_sb"))).where(F.col("likeness") >= least).select("a", "b", "likeness"))


def signature_classes(docs: DataFrame) -> DataFrame:
    """(_f, class_id, _s, _n, _c): each different signature set once, its fingerprint, smallest doc_id, length and a number."""
    sets = with_signatures(docs.select("doc_id", C.text_or_empty("text").alias("_text")), "_text", "_s").select("doc_id", fingerprint(F.col("_s")).alias("_f"), "_s")
    classes = sets.groupBy("_f").agg(F.min("doc_id").alias("class_id"), F.first("_s").alias("_s"))
    return C.cut(classes.withColumn("_n", F.size("_s")).withColumn("_c", F.monotonically_increasing_id()))


def _lists(classes: DataFrame, least: float, hot: int) -> DataFrame:
    """(_x, _b, _c, _n): the lists in which sets meet, by signature and length band.

    Of a set of n signatures the first n - ceil(least * n) + 1 in one order that holds for all are
    dealt: two sets that share none of theirs share too few. The order is by hash, but signatures
    dealt by more than `hot` sets come last, so that very common passages meet only where a
    set has little else. Bands are a factor of 1 / least wide, so sets as alike are at most one
    apart, and each set is in the lists of its band and of the one below.
    """
    first = F.col("_n") - F.ceil(F.col("_n") * F.lit(least) - 1e-9).cast("int") + 1
    band = F.floor(F.log(F.col("_n").cast("double")) / -F.log(F.lit(least)) + 1e-9).cast("int")
    sets = classes.select("_c", "_n", band.alias("_b"), first.alias("_p"), "_s")
    head = C.cut(sets.select("_c", "_n", "_b", F.explode(F.slice(F.sort_array("_s"), F.lit(1), F.col("_p"))).alias("_x")))
    often = C.cut(head.groupBy("_x").agg(F.count(F.lit(1)).alias("_m")).where(F.col("_m") > hot).select("_x"))
    if often.limit(1).count():
        few = C.maybe_broadcast(often)
        moved = C.cut(head.join(few, "_x", "left_semi").select("_c").distinct())
        short = C.maybe_broadcast(moved)
        each = sets.join(short, "_c", "left_semi").select("_c", "_n", "_b", "_p", F.explode("_s").alias("_x")).join(few.withColumn("_o", F.lit(1)), "_x", "left")
        order = Window.partitionBy("_c").orderBy(F.coalesce("_o", F.lit(0)), "_x")
        again = each.withColumn("_r", F.row_number().over(order)).where("_r <= _p").select("_c", "_n", "_b", "_x")
        head = head.join(short, "_c", "left_anti").select("_c", "_n", "_b", "_x").unionByName(again)
    return C.cut(head.select("_x", F.explode(F.array(F.col("_b"), F.col("_b") - 1)).alias("_b"), "_c", "_n"))


def _pairs_of(members: DataFrame, least: float, apart: str = "true") -> DataFrame:
    """All pairs (a, b) of members(_x, _b, _c, _n, ...) of a list whose lengths allow the likeness, and for which `apart` holds."""
    a, b = members.alias("p"), members.alias("q")
    long = F.least("p._n", "q._n") >= F.greatest("p._n", "q._n") * least
    return a.join(b, (F.col("p._x") == F.col("q._x")) & (F.col("p._b") == F.col("q._b")) & (F.col("p._c") < F.col("q._c"))).where(long & F.expr(apart)).select(F.col("p._c").alias("a"), F.col("q._c").alias("b"))


def near_duplicates(docs: DataFrame, least: float = LIKENESS) -> tuple[DataFrame, DataFrame]:
    """(members: doc_id, class_id), (links: a, b, likeness): classes of equal signature sets, and all pairs of class ids with likeness >= least, for tables whose groups of near copies are small."""
    classes = signature_classes(docs)
    sets = with_signatures(docs.select("doc_id", C.text_or_empty("text").alias("_text")), "_text", "_s").select("doc_id", fingerprint(F.col("_s")).alias("_f"))
    members = sets.join(classes.select("_f", "class_id"), "_f").select("doc_id", "class_id")
    links = _verified(_pairs_of(_lists(classes, least, HOT), least), classes, least)
    name = classes.select("_c", "class_id")
    links = links.join(name.withColumnsRenamed({"_c": "a", "class_id": "_a"}), "a").join(name.withColumnsRenamed({"_c": "b", "class_id": "_e"}), "b")
    return members, links.select(F.least("_a", "_e").alias("a"), F.greatest("_a", "_e").alias("b"), "likeness")


def near_groups(docs: DataFrame, least: float = LIKENESS, long: int = LONG, pairs: int = PAIRS, hot: int = HOT, rounds: int = ROUNDS) -> DataFrame:
    """(_f, class_id, component_id): for each signature set the smallest doc_id that has it, and the smallest that links of likeness >= least reach.

    Short lists give all their pairs. In long lists each set is first compared with one set of
    the largest part of one of its lists, a pair a set and round: what is linked so needs no
    pairs among itself. Rounds go on as long as the pairs that could still join two components
    are many; then those pairs are compared. No pair that could change a component is left out.
    """
    classes = signature_classes(docs)
    lists = _lists(classes, least, hot)
    size = C.cut(lists.groupBy("_x", "_b").agg(F.count(F.lit(1)).alias("_m")).where("_m > 1"))
    few = C.maybe_broadcast(size.where(F.col("_m") <= long).select("_x", "_b"))
    links = _verified(_pairs_of(lists.join(few, ["_x", "_b"], "left_semi"), least), classes, least).select("a", "b")
    left = C.cut(lists.join(C.maybe_broadcast(size.where(F.col("_m") > long).select("_x", "_b")), ["_x", "_b"], "left_semi"))
    n = left.count()
    for done in range(rounds + 1):
        if not n:
            break
        label = C.connected(links)
        told = C.cut(left.join(label.withColumnRenamed("node", "_c"), "_c", "left").select("_x", "_b", "_c", "_n", F.coalesce("component", "_c").alias("_l")))
        groups = told.groupBy("_x", "_b", "_l").agg(F.count(F.lit(1)).alias("_g"), F.min(F.struct("_c", "_n")).alias("_one"))
        head = F.max_by(F.struct(F.col("_one._c"), F.col("_one._n"), F.col("_l")), F.struct(F.col("_g"), -F.col("_l")))
        open_ = C.cut(groups.groupBy("_x", "_b").agg(F.sum("_g").alias("_m"), F.sum(F.col("_g") * F.col("_g")).alias("_q"), F.count(F.lit(1)).alias("_parts"), head.alias("_first")).where("_parts > 1"))
        rest = open_.agg(F.sum((F.col("_m") * F.col("_m") - F.col("_q")) / 2)).first()[0] or 0
        if not rest:
            break
        told = told.join(C.maybe_broadcast(open_.select("_x", "_b", "_first")), ["_x", "_b"])
        if rest <= pairs * n or done == rounds:
            links = links.union(_verified(_pairs_of(told, least, "p._l <> q._l"), classes, least).select("a", "b"))
            break
        near = (F.col("_l") != F.col("_first._l")) & (F.least("_n", "_first._n") >= F.greatest("_n", "_first._n") * least)
        star = told.where(near).groupBy(F.col("_c").alias("b")).agg(F.min("_first._c").alias("a"))
        links = C.cut(links.union(_verified(star.select("a", "b"), classes, least).select("a", "b")))
    label = C.connected(links)
    named = classes.select("_f", "class_id", "_c").join(label, F.col("_c") == F.col("node"), "left").withColumn("_l", F.coalesce("component", "_c"))
    least_id = C.cut(label.select(F.col("node").alias("_c"), F.col("component").alias("_l")).join(classes.select("_c", "class_id"), "_c").groupBy("_l").agg(F.min("class_id").alias("_least")))
    return C.cut(named.join(C.maybe_broadcast(least_id), "_l", "left").select("_f", "class_id", F.coalesce("_least", "class_id").alias("component_id")))


def op9_spotsigs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_edited(C.table(spark, sf_dir, "documents"))


def spotsigs_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with class_id, the smallest doc_id with the same signatures, and component_id, the smallest that near duplicates reach."""
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text")
    own = with_signatures(docs.select("doc_id", C.text_or_empty("text").alias("_text")), "_text", "_s").select("doc_id", fingerprint(F.col("_s")).alias("_f"))
    return own.join(near_groups(docs), "_f").select("doc_id", "class_id", "component_id")
