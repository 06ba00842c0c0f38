"""Near-duplicate embeddings by navigable small-world graphs.

Equal vectors are one node. Nodes are dealt to shards, whose number follows the number of nodes, so a shard keeps its size. A task builds the graph of one shard and
then reads a share of all nodes, in a stream, as queries against it; several tasks, more of them the more shards there are, do so for each shard, and the building is
a small part of what each does. So every node is compared with every shard and no task holds more than a shard and a batch. Beams are widened for the whole shard
until an audit against all its nodes finds enough of planted and real neighbours, and for a query as long as neighbours fill its beam. What is found is verified by cosine in double precision. A task gives
out a row for each query that has links, with their number and one of them, and a row whenever a query joins two groups of its shard: as many rows as
nodes, not as pairs, with the same components. Links are counted where they are found, copies included.

Nulls: a vector that is null, empty, zero or holds a null or non-finite number links with nothing and stays. A null id counts for nothing in the least id.
Vectors of different lengths aren't compared. Repeated rows are copies. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.llm.common import table, written
from accord.llm.components import connected_components

#: Nodes of a shard, shards at least, shards' worth of queries that a task asks for each graph that it builds.
SHARD_NODES, SHARDS, ASKED = 32768, 6, 3
#: The first beam, the audit's queries and the share that it must find.
BEAM, AUDIT, RECALL = 48, 128, 0.99
#: Single precision in the search is off by less than this.
SLACK = 1e-4


def _usable(v):
    ok = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))
    return v.isNotNull() & (F.size(v) > 0) & F.forall(v, ok) & F.exists(v, lambda x: x != 0)


def _audited(graph, x, least: float) -> int:
    """The beam at which the audit passes: some members, moved to a cosine near the limit, and their neighbours among all nodes, are found again.
    Each query counts alike, however many neighbours it has."""
    import numpy as np

    n = len(x)
    rng = np.random.default_rng(7)
    own = rng.integers(0, n, min(AUDIT, n))
    some = x[own]
    aside = rng.normal(size=some.shape)
    aside -= (aside * some).sum(axis=1, keepdims=True) * some
    aside /= np.maximum(np.linalg.norm(aside, axis=1, keepdims=True), 1e-12)
    cos = least + 0.1 * (1 - least)
    q = np.concatenate([cos * some + np.sqrt(1 - cos * cos) * aside, some])
    true = q @ x.T >= least
    true[len(own) + np.arange(len(own)), own] = False  # a member finds itself
    sizes = true.sum(axis=1)
    asked = sizes > 0
    ef = BEAM
    while ef < n:
        found = graph.within(q, least - SLACK, ef)
        hits = np.array([t[f].sum() for t, f in zip(true, found)])
        if not asked.any() or (hits[asked] / sizes[asked]).mean() >= RECALL:
            break
        ef *= 2
    return ef


class _Shard:
    """Nodes, their graph, and the groups into which queries have joined them."""

    def __init__(self, least: float) -> None:
        self.least, self.parts, self.graph = least, [], None

    def add(self, nodes, x, copies) -> None:
        self.parts.append((nodes, x, copies))

    def build(self) -> None:
        import numpy as np

        from accord.llm.hnsw import Graph

        self.nodes, self.x, self.copies = (np.concatenate([p[i] for p in self.parts]) for i in range(3))
        order = np.argsort(self.nodes)
        self.nodes, self.x, self.copies = self.nodes[order], self.x[order], self.copies[order]
        self.graph = Graph(self.x)
        self.ef = _audited(self.graph, self.x, self.least)
        self.group = np.arange(len(self.x))
        self.members = [[i] for i in range(len(self.x))]

    def join(self, a: int, b: int) -> int:
        a, b = int(self.group[a]), int(self.group[b])
        if len(self.members[a]) < len(self.members[b]):
            a, b = b, a
        self.group[self.members[b]] = a
        self.members[a] += self.members[b]
        self.members[b] = []
        return a

    def ask(self, nodes, x):
        """Rows (a, b, links): a query, a node of the shard that it is linked with, how many vectors those links stand for; links 0: only joined."""
        import numpy as np

        if not self.parts:  # no vector of this length is in the shard
            return []
        if self.graph is None:
            self.build()
        out = []
        for i, near in enumerate(self.graph.within(x, self.least - SLACK, self.ef)):
            if not len(near):
                continue
            near = near[(self.x[near] @ x[i] >= self.least) & (self.nodes[near] != nodes[i])]
            if not len(near):
                continue
            out.append((nodes[i], self.nodes[near[0]], int(self.copies[near].sum())))
            for g in np.unique(self.group[near]):
                if self.group[near[0]] != self.group[g]:
                    out.append((self.nodes[near[0]], self.nodes[g], 0))
                    self.join(near[0], g)
        return out


def links(nodes: DataFrame, least: float, shards: int) -> DataFrame:
    """(a, b, links) as _Shard.ask() gives them, for nodes (node, vector, copies)."""
    splits = max(2, shards // ASKED)

    def run(batches):
        import numpy as np
        import pyarrow as pa

        at, shard = None, None
        for b in batches:
            cols = {n: b.column(i) for i, n in enumerate(b.schema.names)}
            dim, own, split, ask = (cols[n].to_numpy(zero_copy_only=False) for n in ("dim", "shard", "split", "ask"))
            node, copies = cols["node"].to_numpy(), cols["copies"].to_numpy()
            lists = cols["vector"]
            flat, ends = lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64), np.concatenate([[0], np.cumsum(dim)])
            cuts = np.nonzero((np.diff(dim) != 0) | (np.diff(own) != 0) | (np.diff(split) != 0) | (np.diff(ask) != 0))[0] + 1
            rows = []
            for i, j in zip([0, *cuts], [*cuts, len(node)]):
                if i == j:
                    continue
                if at != (dim[i], own[i], split[i]):
                    at, shard = (dim[i], own[i], split[i]), _Shard(least)
                x = flat[ends[i] : ends[j]].reshape(j - i, -1)
                x = x / np.abs(x).max(axis=1, keepdims=True)
                x /= np.linalg.norm(x, axis=1, keepdims=True)
                if ask[i]:
                    for k in range(0, j - i, 1024):
                        rows += shard.ask(node[i:j][k : k + 1024], x[k : k + 1024])
                else:
                    shard.add(node[i:j], x, copies[i:j])
            cut = list(zip(*rows)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(np.array(c, np.int64)) for c in cut], names=["a", "b", "links"])

    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    dealt = lambda n, seed: F.pmod(F.xxhash64("node", F.lit(seed)), F.lit(n)).cast("int")
    mine = nodes.withColumns({"shard": dealt(shards, 0), "split": each(splits), "ask": F.lit(0)})
    asked = nodes.withColumns({"shard": each(shards), "split": dealt(splits, 1), "ask": F.lit(1)})
    both = mine.unionByName(asked).withColumn("dim", F.size("vector"))
    both = both.repartition(4 * shards * splits, "dim", "shard", "split").sortWithinPartitions("dim", "shard", "split", "ask")
    return both.select("dim", "shard", "split", "ask", "node", "copies", "vector").mapInArrow(run, "a bigint, b bigint, links bigint")


def near_duplicates(rows: DataFrame, key: str = "vec_id", vector: str = "embedding", least: float = 0.95, shards: int | None = None) -> DataFrame:
    """(key, n_links, component_id) for each row; shards None: as many as their size asks for."""
    v = F.col(f"`{vector}`")
    rows = rows.select(F.col(f"`{key}`").alias("id"), v.alias("vector"), _usable(v).alias("usable"))
    per = rows.where("usable").groupBy("vector").agg(F.count("*").alias("copies"), F.min("id").alias("least"))
    nodes = written(per.withColumn("node", F.monotonically_increasing_id()), "vectors")
    shards = shards or max(SHARDS, -(-nodes.count() // SHARD_NODES))
    found = written(links(nodes.select("node", "vector", "copies"), least, shards), "links")
    roots = connected_components(found)
    counted = found.where("links > 0").groupBy(F.col("a").alias("linked")).agg(F.sum("links").alias("others"))
    one = nodes.join(roots, "node", "left").join(counted, F.col("node") == F.col("linked"), "left")
    one = written(one.select("vector", "copies", "least", F.coalesce("root", "node").alias("group"), F.coalesce("others", F.lit(0)).alias("others")), "linked")
    least_of = one.groupBy("group").agg(F.min("least").alias("component_id"))
    told = one.join(least_of, "group").select(F.col("vector").alias("its"), (F.col("others") + F.col("copies") - 1).alias("n_links"), "component_id")
    good = rows.where("usable").join(told, (F.xxhash64("vector") == F.xxhash64("its")) & (F.col("vector") == F.col("its"))).select("id", "n_links", "component_id")
    alone = rows.where("not usable").select("id", F.lit(0).cast("bigint").alias("n_links"), F.col("id").alias("component_id"))
    return good.union(alone).withColumnRenamed("id", key)


def op8_vectors(spark, sf_dir: str) -> DataFrame:
    out = near_duplicates(table(spark, sf_dir, "embeddings", "vec_id", "embedding"))
    return out.withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


OP8_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, embedding::DOUBLE[] AS e, embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0 AS usable FROM embeddings
), l AS (
  SELECT a.vec_id AS x, b.vec_id AS y FROM (SELECT * FROM v WHERE usable) a JOIN (SELECT * FROM v WHERE usable) b ON a.vec_id <> b.vec_id AND len(a.e) = len(b.e) AND list_cosine_similarity(a.e, b.e) >= 0.95
), r AS (
  SELECT vec_id, vec_id AS y FROM v UNION SELECT r.vec_id, l.y FROM r JOIN l ON l.x = r.y
)
SELECT v.vec_id, coalesce(n.n, 0)::BIGINT AS n_links, c.component_id, v.vec_id = c.component_id AS kept
FROM v LEFT JOIN (SELECT x, count(*) AS n FROM l GROUP BY x) n ON n.x = v.vec_id JOIN (SELECT vec_id, min(y) AS component_id FROM r GROUP BY vec_id) c USING (vec_id)
"""
