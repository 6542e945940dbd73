"""SQL surface: scalar functions as SQL expressions and an ordered table function that partitions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..kernel.greedy import Greedy
from ..params import PartitionSpec


@udtf(returnType="graph_id bigint, seq bigint, vertex_id bigint, block int")
class StreamPartition:
    """stream_partition(TABLE(t) PARTITION BY graph_id ORDER BY (seq), k, eps, objective, n, m).

    t: graph_id, seq, vertex_id, nets (array of net ids). n, m: vertices and nets, known to the caller."""

    def __init__(self):
        self.engine = None

    def eval(self, row, k: int, eps: str, objective: str, n: int, m: int):
        if self.engine is None:
            spec = PartitionSpec(int(k), str(eps), str(objective))
            self.engine = Greedy(spec, spec.capacity(int(n)), spec.strength(int(n), int(m)))
        block = self.engine.place(1.0, [(net, 1.0) for net in row["nets"] or ()])[0]
        yield row["graph_id"], row["seq"], row["vertex_id"], block


@udtf(returnType="vertex_id bigint")
class NetPins:
    """net_pins(line): the vertex ids of a net-list line."""

    def eval(self, line: str):
        for x in (line or "").split():
            yield (int(x),)


def register(spark: SparkSession) -> None:
    spark.udtf.register("stream_partition", StreamPartition)
    spark.udtf.register("net_pins", NetPins)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash_block(id BIGINT, k INT) RETURNS INT RETURN CAST(CAST(conv(substr(md5(CAST(id AS STRING)), 1, 8), 16, 10) AS BIGINT) % k AS INT)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION load_penalty(load DOUBLE, strength DOUBLE) RETURNS DOUBLE RETURN strength * sqrt(load)")
