"""Sharding by a hierarchical weighted hash tree.

A document descends from the root over region and rack to a shard.  At each node every child draws -ln(u) / weight, with
u a uniform hash of (doc_id, the child's name), and the least draw wins: children win in proportion to their weights,
and a change of one child's weight moves only documents to or from that child.  Movement is so confined to subtrees
whose weights change: a shard added as a region of its own takes documents only into itself, and no other moves.

Law ``key``: doc_id and the tree decide alone.  Defined results: a null doc_id hashes as the word null; a null text has
no bytes (size 1, checksum 0); rows that repeat a doc_id go to the same shard, each with a slot of its own; other
columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .exchange import ranked

_SPAN = 1 << 52


@dataclass(frozen=True)
class Node:
    """A region, rack or shard: leaves have a shard number and a weight, others the sum of their children's."""

    name: str
    children: tuple[Node, ...] = ()
    shard: int | None = None
    own_weight: float = 1.0

    @property
    def weight(self) -> float:
        return sum(c.weight for c in self.children) if self.children else self.own_weight


def tree(shards: int, per_rack: int = 2, racks: int = 2, base: int = 8) -> Node:
    """The tree of a number of shards: ``base`` of them share racks and regions, every later one is a region alone.

    The tree of n + 1 shards beyond the base is that of n with one more region, so growth moves documents only there.
    """
    leaves = [Node(f"shard{i}", shard=i) for i in range(min(shards, base))]
    racked = [Node(f"rack{i}", tuple(leaves[i * per_rack : (i + 1) * per_rack])) for i in range(-(-len(leaves) // per_rack))]
    regions = [Node(f"region{i}", tuple(racked[i * racks : (i + 1) * racks])) for i in range(-(-len(racked) // racks))]
    extra = [Node(f"region+{i}", (Node(f"rack+{i}", (Node(f"shard{i}", shard=i),)),)) for i in range(base, shards)]
    return Node("root", (*regions, *extra))


def draw_sql(key: str, node: Node) -> str:
    """Spark SQL of a child's draw: -ln(u) / weight, u from the first 52 bits of an md5."""
    return f"-ln((cast(conv(substr(md5(concat({key}, '/{node.name}')), 1, 13), 16, 10) as double) + 1) / {_SPAN + 1}D) / {node.weight!r}D"


def descend(key: str, node: Node) -> str:
    """Spark SQL of the shard that the key reaches below a node."""
    if node.shard is not None:
        return str(node.shard)
    if len(node.children) == 1:
        return descend(key, node.children[0])
    best = "least(" + ", ".join(f"struct({draw_sql(key, c)} as draw, {i} as child)" for i, c in enumerate(node.children)) + ").child"
    return f"case {best} " + " ".join(f"when {i} then {descend(key, c)}" for i, c in enumerate(node.children)) + " end"


def shard_of(key: str, node: Node) -> Column:
    return F.expr(descend(f"coalesce(cast({key} as string), 'null')", node)).cast("int")


def shard_documents(docs: DataFrame, shards: int = 8, grown: int | None = 9) -> DataFrame:
    """docs(doc_id, text) -> doc_id, size, text_crc32, law, shard, slot (gapless, by doc_id), grown_shard."""
    raw = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    dealt = docs.select(
        "doc_id",
        (F.octet_length(raw) + 1).cast("long").alias("size"),
        F.crc32(raw).alias("text_crc32"),
        F.lit("key").alias("law"),
        shard_of("doc_id", tree(shards)).alias("shard"),
        (shard_of("doc_id", tree(grown)) if grown else F.lit(None).cast("int")).alias("grown_shard"),
    )
    return ranked(dealt, "shard", ["doc_id", "text_crc32", "size"], "slot").select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")


def duckdb_shard(key: str, node: Node) -> str:
    """The same descent as DuckDB SQL, for the oracle."""
    if node.shard is not None:
        return str(node.shard)
    if len(node.children) == 1:
        return duckdb_shard(key, node.children[0])
    draws = [f"-ln((('0x' || substr(md5({key} || '/{c.name}'), 1, 13))::BIGINT::DOUBLE + 1) / {_SPAN + 1}::DOUBLE) / {c.weight!r}::DOUBLE" for c in node.children]
    best = "list_position([" + ", ".join(draws) + "], list_min([" + ", ".join(draws) + "]))"
    return f"(case {best} " + " ".join(f"when {i + 1} then {duckdb_shard(key, c)}" for i, c in enumerate(node.children)) + " end)"


def oracle(shards: int = 8, grown: int = 9) -> str:
    """DuckDB SQL of op4's rows; the checksum folds the bytes through the usual table of 256 remainders."""
    key = "coalesce(cast(doc_id as varchar), 'null')"
    step = "case when (x & 1) = 1 then xor(x >> 1, 3988292384) else x >> 1 end"
    table = "r0"
    for _ in range(8):
        table = f"list_transform({table}, lambda x: {step})"
    return f"""
with t as (select {table} as crc from (select list_transform(range(256), lambda x: x::BIGINT) as r0)),
bytes as (select doc_id, coalesce(text, '') as text, hex(encode(coalesce(text, ''))) as h from documents),
d as (select doc_id, cast(length(h) // 2 + 1 as bigint) as size,
  cast(xor(list_reduce(list_transform(range(0, length(h) // 2), lambda i: ('0x' || substr(h, 2 * i + 1, 2))::BIGINT),
    lambda a, b: xor(a >> 8, crc[xor(a, b) % 256 + 1]), 4294967295::BIGINT), 4294967295::BIGINT) as bigint) as text_crc32,
  {duckdb_shard(key, tree(shards))} as shard, {duckdb_shard(key, tree(grown))} as grown_shard from bytes, t)
select doc_id, size, text_crc32, 'key' as law, cast(shard as int) as shard,
  cast(row_number() over (partition by shard order by doc_id nulls first, text_crc32, size) - 1 as bigint) as slot,
  cast(grown_shard as int) as grown_shard from d"""
