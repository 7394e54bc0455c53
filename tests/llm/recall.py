"""python tests/llm/recall.py [SF_DIR]: what op1's fingerprints and the pipeline's near-copy stage find of all pairs of different texts that are alike; one JSON line."""

from __future__ import annotations

import json
import os
import sys
from collections import Counter, defaultdict
from math import ceil

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__)))))


def shingles(text: str | None, words: int = 5) -> frozenset[tuple[bytes, ...]]:
    w = (text or "").encode().lower().split()
    return frozenset(tuple(w[k : k + words]) for k in range(max(1, len(w) - words + 1)))


def alike_pairs(texts: list[str], least: float = 0.8) -> list[tuple[int, int, float]]:
    """(i, j, likeness) of all pairs of `texts` with likeness `least` or more: exact, since two such sets share one of their rarest shingles."""
    sets = [shingles(t) for t in texts]
    often = Counter(s for one in sets for s in one)
    lists = defaultdict(list)
    for i, one in enumerate(sets):
        rare = sorted(one, key=lambda s: (often[s], s))
        for s in rare[: len(rare) - ceil(least * len(rare) - 1e-9) + 1]:
            lists[s].append(i)
    out = []
    for i, j in {(i, j) for at in lists.values() for i in at for j in at if i < j}:
        a, b = sets[i], sets[j]
        if min(len(a), len(b)) >= least * max(len(a), len(b)) - 1e-9:
            both = len(a & b)
            like = both / (len(a) + len(b) - both)
            if like >= least:
                out.append((i, j, like))
    return out


def measured(spark, docs, steps: tuple[float, ...] = (0.8, 0.9, 0.95)) -> dict:
    """For each step: pairs of at least that likeness, the share that op1's fingerprints link, and the share that the stage does not keep whole."""
    from verbatim.llm import simhash

    first = {}
    for r in docs.where("doc_id is not null").select("doc_id", "text").orderBy("doc_id").collect():
        first.setdefault(r.text or "", r.doc_id)
    texts, ids = list(first), list(first.values())
    label = {r.doc_id: r.component_id for r in simhash.components(simhash.fingerprints(docs)).collect()}
    kept = {r.doc_id for r in simhash.deduplicate(docs).select("doc_id").collect()}
    pairs, out = alike_pairs(texts), {}
    for least in steps:
        some = [(ids[i], ids[j]) for i, j, like in pairs if like >= least]
        share = lambda good: round(sum(map(good, some)) / len(some), 4) if some else None
        out[str(least)] = {"pairs": len(some), "op1": share(lambda p: label[p[0]] == label[p[1]]), "stage": share(lambda p: not (p[0] in kept and p[1] in kept))}
    near = {x for i, j, _ in pairs for x in (ids[i], ids[j])}
    out["gone without a like text"] = len(set(ids) - kept - near)
    return out


def main() -> None:
    from pyspark.sql import SparkSession

    sf = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.1"
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    print(json.dumps({"sf": os.path.basename(sf.rstrip("/")), **measured(spark, spark.read.parquet(f"{sf}/documents.parquet"))}))
    spark.stop()


if __name__ == "__main__":
    main()
