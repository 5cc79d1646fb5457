"""Training features from the graph: neighbourhood triplets and routing traces.

Neighbourhood: the vertices within n hops of an anchor, ranked by original distance; the nearest k_pos are its
positive scope and the next k_neg its negative scope; each epoch draws one of each by a hash. Routing: beam
searches of sampled queries, their ranked candidate list after every hop and the vertex visited next, labelled
by a teacher.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecgraph.functions.columns import d2, draw_key
from vecgraph.session import materialize

from .quantize import Quantizer
from .walk import Index, code_distance, run_shards, walk


def n_hop(edges: DataFrame, n: int, expansion: str = "n_hops", anchors: DataFrame | None = None) -> DataFrame:
    """(anchor, vid): different vertices within n hops, the anchor left out; of all vertices, or of `anchors` (anchor).
    "extra_ring" adds one more hop, as the printed loop does."""
    step = edges.select(F.col("src").alias("vid"), F.col("dst").alias("next")).distinct()
    found = edges.select(F.col("src").alias("anchor"), F.col("dst").alias("vid")).distinct()
    if anchors is not None:
        found = found.join(anchors, "anchor", "left_semi")
    for _ in range(n - 1 if expansion == "n_hops" else n):
        grown = found.join(step, "vid").select("anchor", F.col("next").alias("vid"))
        found = found.unionByName(grown).distinct()
    return found.where("anchor <> vid")


def scopes(population: DataFrame, base: DataFrame, k_pos: int, k_neg: int) -> DataFrame:
    """(anchor, vid, rank, scope): the k_pos nearest and the k_neg after them; anchors with too few are dropped."""
    a = base.select(F.col("id").alias("anchor"), F.col("vec").alias("va"))
    v = base.select(F.col("id").alias("vid"), F.col("vec").alias("vv"))
    dist = population.join(a, "anchor").join(v, "vid").select("anchor", "vid", d2(F.col("va"), F.col("vv")).alias("d2"))
    rank = F.row_number().over(Window.partitionBy("anchor").orderBy("d2", "vid"))
    first = dist.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k_pos + k_neg)
    whole = first.withColumn("n", F.count("*").over(Window.partitionBy("anchor"))).where(F.col("n") == k_pos + k_neg)
    return whole.select("anchor", "vid", "rank", F.when(F.col("rank") <= k_pos, "pos").otherwise("neg").alias("scope"))


def draw(scope_rows: DataFrame, epoch: int, seed: int) -> DataFrame:
    """(anchor, scope, vid): one member of each scope, uniform by hash and the same wherever it is drawn."""
    key = draw_key(F.lit(seed), F.lit(epoch), F.col("anchor"), F.col("scope"), F.col("vid"))
    return scope_rows.groupBy("anchor", "scope").agg(F.min(F.struct(key.alias("key"), "vid")).alias("b")).select("anchor", "scope", F.col("b.vid").alias("vid"))


def triplets(scope_rows: DataFrame, epoch: int, seed: int) -> DataFrame:
    """(anchor, pos, neg, epoch)."""
    drawn = draw(scope_rows, epoch, seed)
    both = drawn.groupBy("anchor").agg(F.max(F.when(F.col("scope") == "pos", F.col("vid"))).alias("pos"), F.max(F.when(F.col("scope") == "neg", F.col("vid"))).alias("neg"))
    return both.where("pos is not null and neg is not null").withColumn("epoch", F.lit(epoch))


def naive_triplets(base: DataFrame, edges: DataFrame, epoch: int, seed: int, buckets: int = 1024, tries: int = 8) -> DataFrame:
    """(anchor, pos, neg, epoch) of the sampler to compare with: a positive from the neighbours, a negative from all other vertices.

    Each epoch draws one vertex per hash bucket; an anchor's tries name buckets, and the first whose vertex is neither
    the anchor nor its neighbour is the negative. Anchors all of whose tries fail take, of all vertices in the order of the
    epoch's hash, the first that fits: one of the first degree + 2, so no more of them are looked at. Only anchors that are
    linked with every other vertex are left out.
    """
    pos = edges.groupBy(F.col("src").alias("anchor")).agg(F.min(F.struct(draw_key(F.lit(seed), F.lit(epoch), F.col("src"), F.col("dst")).alias("key"), "dst")).alias("b")).select("anchor", F.col("b.dst").alias("pos"))
    number = lambda key: F.conv(F.substring(key, 1, 8), 16, 10).cast("long") % buckets
    key = draw_key(F.lit(seed), F.lit(epoch), F.col("id"))
    drawn = base.groupBy(number(F.md5(F.col("id").cast("string"))).alias("bucket")).agg(F.min(F.struct(key.alias("key"), "id")).alias("b")).select("bucket", F.col("b.id").alias("neg"))
    anchor = base.select(F.col("id").alias("anchor"), F.explode(F.sequence(F.lit(0), F.lit(tries - 1))).alias("try"))
    asked = anchor.withColumn("bucket", number(draw_key(F.lit(seed), F.lit(epoch), F.col("anchor"), F.col("try"))))
    cand = asked.join(F.broadcast(drawn), "bucket").where("neg <> anchor")  # one row per bucket
    free = cand.join(edges.select(F.col("src").alias("anchor"), F.col("dst").alias("neg")), ["anchor", "neg"], "left_anti")
    neg = materialize(free.groupBy("anchor").agg(F.min(F.struct("try", "neg")).alias("b")).select("anchor", F.col("b.neg").alias("neg")))
    links = edges.select(F.col("src").alias("anchor"), F.col("dst").alias("neg")).distinct()
    left = materialize(pos.join(neg, "anchor", "left_anti").select("anchor"))
    most = left.join(links, "anchor").groupBy("anchor").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0]
    if most is not None:
        order = [r.id for r in base.select("id", key.alias("key")).orderBy("key", "id").limit(most + 2).collect()]  # at most the largest degree and two
        taken = links.join(left, "anchor").groupBy("anchor").agg(F.collect_set("neg").alias("taken"))
        free = F.filter(F.lit(order).cast("array<long>"), lambda v: (v != F.col("anchor")) & ~F.array_contains("taken", v))
        rest = taken.select("anchor", F.get(free, F.lit(0)).alias("neg"))
        neg = neg.unionByName(rest.where("neg is not null"))
    return pos.join(neg, "anchor").select("anchor", "pos", "neg", F.lit(epoch).alias("epoch"))


def sample_queries(base: DataFrame, m: int, seed: int) -> DataFrame:
    """m rows in a hash order."""
    key = draw_key(F.lit(seed), F.col("id"))
    return base.orderBy(key, "id").limit(m)


TRACE = "qid long, step int, cands array<struct<d2:double,vid:long,seen:boolean>>, next_vid long"


def routing_traces(index: DataFrame, queries: DataFrame, quantizer: Quantizer, h: int) -> DataFrame:
    """(qid, step, cands, next_vid): the list after each hop, with flags of what has been visited, and the vertex visited
    from it next; the last list of a search has none."""

    def kernel(idx: Index, ids: np.ndarray, q: np.ndarray) -> Iterator[pa.RecordBatch]:
        w = walk(idx, len(q), code_distance(idx, quantizer.lut(q)), h, trace=True)
        for i, (rows, place, d, seen, to) in enumerate(w.steps):
            ok = place < len(idx.ids)
            kept = [d[ok], idx.ids[place[ok]], seen[ok]]
            ends = np.concatenate([[0], np.cumsum(ok.sum(1))]).astype(np.int32)
            cands = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(x) for x in kept], ["d2", "vid", "seen"]))
            nxt = pa.array(idx.ids[np.maximum(to, 0)], mask=to < 0)
            yield pa.RecordBatch.from_arrays([pa.array(ids[rows]), pa.array(np.full(len(rows), i, np.int32)), cands, nxt], ["qid", "step", "cands", "next_vid"])

    return run_shards(index, queries, kernel, TRACE)


def label_traces(traces: DataFrame, base: DataFrame, queries: DataFrame, teacher: str = "exact", edges: DataFrame | None = None) -> DataFrame:
    """(qid, step, label): the unvisited candidate that a teacher would visit next.

    "exact": nearest to the query by original distance; "selected": the one the search visited; "hop_oracle": fewest
    hops to the query's true nearest vertex (`edges` needed), then original distance.
    """
    if teacher == "selected":
        return traces.where("next_vid is not null").select("qid", "step", F.col("next_vid").alias("label"))
    open_ = traces.where("next_vid is not null").select("qid", "step", F.explode("cands").alias("c")).where("not c.seen").select("qid", "step", F.col("c.vid").alias("vid"))
    if teacher == "hop_oracle":
        open_ = materialize(open_)
    q = queries.select(F.col("id").alias("qid"), F.col("vec").alias("qv"))
    v = base.select(F.col("id").alias("vid"), "vec")
    dist = open_.join(q, "qid").join(v, "vid").select("qid", "step", "vid", d2(F.col("qv"), F.col("vec")).alias("d2"))
    if teacher == "exact":
        return dist.groupBy("qid", "step").agg(F.min(F.struct("d2", "vid")).alias("b")).select("qid", "step", F.col("b.vid").alias("label"))
    far = hops_to_nearest(base, queries, edges, open_)
    both = dist.join(far, ["qid", "vid"], "left").withColumn("hops", F.coalesce("hops", F.lit(1 << 20)))
    return both.groupBy("qid", "step").agg(F.min(F.struct("hops", "d2", "vid")).alias("b")).select("qid", "step", F.col("b.vid").alias("label"))


def hops_to_nearest(base: DataFrame, queries: DataFrame, edges: DataFrame, wanted: DataFrame | None = None) -> DataFrame:
    """(qid, vid, hops): hops from each vertex to the query's nearest vertex, of all pairs, or of the `wanted` (qid, vid).

    Backwards from the nearest vertices, one join per ring, 64 queries together: a row is a vertex and a word of 64 queries, a bit
    for each that has come to it. So rows are vertices times words, not vertices times queries.
    """
    from .exact import exact_knn

    near = materialize(exact_knn(base, queries, 1).select("qid", "vid"))
    # queries are numbered without gaps, but for one at most per 65,536 of them
    goal = materialize(near.coalesce(max(1, near.count() >> 16)).withColumn("no", F.monotonically_increasing_id()))
    word, bit = F.shiftright("no", 6).alias("word"), F.expr("shiftleft(1L, cast(no & 63 as int))")
    front = seen = materialize(goal.groupBy("vid", word).agg(F.bit_or(bit).alias("bits")))
    back = materialize(edges.select(F.col("dst").alias("vid"), F.col("src").alias("prev")).distinct())
    rings = []
    while not front.isEmpty():
        rings.append(front.withColumn("hops", F.lit(len(rings))))
        come = front.join(back, "vid").groupBy(F.col("prev").alias("vid"), "word").agg(F.bit_or("bits").alias("come"))
        met = come.join(seen.withColumnRenamed("bits", "had"), ["vid", "word"], "full_outer").na.fill(0, ["come", "had"])
        met = materialize(met.select("vid", "word", "had", F.col("come").bitwiseAND(F.bitwise_not("had")).alias("new")))
        front = met.where("new <> 0").select("vid", "word", F.col("new").alias("bits"))
        seen = met.select("vid", "word", F.col("had").bitwiseOR(F.col("new")).alias("bits"))
    found = None
    for ring in rings:
        found = ring if found is None else found.unionByName(ring)
    if found is None:
        return goal.select("qid", "vid", F.lit(0).alias("hops"))
    if wanted is not None:
        asked = wanted.select("qid", "vid").distinct().join(goal.select("qid", "no"), "qid").groupBy("vid", word).agg(F.bit_or(bit).alias("asked"))
        found = found.join(materialize(asked), ["vid", "word"]).withColumn("bits", F.col("bits").bitwiseAND(F.col("asked"))).where("bits <> 0")
    each = found.select("vid", "word", "bits", "hops", F.explode(F.sequence(F.lit(0), F.lit(63))).alias("at")).where("shiftright(bits, at) & 1 = 1")
    return each.withColumn("no", F.expr("word * 64 + at")).join(goal.select("qid", "no"), "no").select("qid", "vid", "hops")
