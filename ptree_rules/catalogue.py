"""The registered queries and their SQL equivalents. Each takes (spark, sf_dir) and reads whole tables."""

from __future__ import annotations

import uuid
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions import discretize, measures
from .functions.bits import and_mask, morton, padded_slots, register_sql
from .operators import anding, candidates, items, ptree, segment_trees, tids
from .operators import rules as R
from .plans import baselines, grid
from .plans.miner import Trees, append_segments, frequent_items, mine_ptree, mine_segmented
from .sources import tables
from .sources import workloads as W
from .sources.tables import load
from .streaming import windows

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
FLAT = ("antecedent", "consequent", "k", "cnt_xy", "cnt_x", "n", "support", "confidence", "decision")


def query(sql: str | None = None, name: str | None = None):
    def put(f):
        QUERIES[name or f.__name__] = f
        if sql is not None:
            ORACLE_SQL[name or f.__name__] = sql
        return f

    return put


def _frame(spark: SparkSession, rows: list, schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# Encoding.


@query("SELECT l_orderkey, l_linenumber, CASE WHEN l_linestatus = 'O' THEN 1 ELSE 0 END AS is_open, CASE WHEN l_linestatus <> 'O' THEN 1 ELSE 0 END AS is_other FROM lineitem")
def bad_encode(spark, sf_dir):
    one, other = items.encode_binary(F.col("l_linestatus") == "O", both_values=True)
    return load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", one.alias("is_open"), other.alias("is_other"))


_BAL = "CASE WHEN c_acctbal < 2000 THEN 'low' WHEN c_acctbal < 6000 THEN 'middle' ELSE 'high' END"


@query(f"SELECT c_custkey, CAST({_BAL} = 'high' AS INTEGER) AS high, CAST({_BAL} = 'middle' AS INTEGER) AS middle, CAST({_BAL} = 'low' AS INTEGER) AS low FROM customer")
def nbad_encode(spark, sf_dir):
    values = ["high", "middle", "low"]
    bits = items.encode_nominal(discretize.band("c_acctbal", (2000, 6000), ("low", "middle", "high")), values)
    return load(spark, sf_dir, "customer").select("c_custkey", *(b.alias(v) for b, v in zip(bits, values, strict=True)))


def _stack_sql(w: str) -> str:
    return " UNION ALL ".join(f"SELECT '{a}' AS attribute, {a} AS value FROM e" for a in O.ATTRIBUTES[w])


@query(f"""WITH e AS ({O.RELATIONS["w1"]}), s AS (SELECT DISTINCT * FROM ({_stack_sql("w1")}) WHERE value IS NOT NULL)
    SELECT CAST(row_number() OVER (ORDER BY attribute, value) - 1 AS INTEGER) AS item_id, attribute, value,
           CASE WHEN count(*) OVER (PARTITION BY attribute) = 1 THEN 'BAD' ELSE 'NBAD' END AS domain, attribute = 'class' AS is_decision FROM s""")
def item_dictionary(spark, sf_dir):
    return items.item_frame(W.w1(spark, sf_dir))


@query(f"""WITH e AS ({O.RELATIONS["w1"]}), s AS ({_stack_sql("w1")}) SELECT attribute, value, count(*) AS cnt FROM s GROUP BY ALL""")
def item_histogram(spark, sf_dir):
    return items.item_counts(W.w1(spark, sf_dir))


def _w1_dense(spark, sf_dir):
    """Order lines numbered by key; the attributes after it decide among the lines that share one."""
    info, df = W.w1(spark, sf_dir), W.w1_keyed(spark, sf_dir)
    return tids.dense_tids(df, [*W.W1_KEY, *info.attributes]).select("tid", *info.attributes), items.build_items(info), info


_W1_ITEMS = {"rf": "ANR", "ls": "FO", "os": "FOP", "qty": ("lo", "mid", "hi"), "disc": ("lo", "mid", "hi"), "class": ("c1", "c2", "c3", "c4"), "oy": range(1995, 2002)}


@query(f"WITH {O.dense()} SELECT tid, " + ", ".join(f"CAST({a} = '{v}' AS INTEGER) AS \"{a}={v}\"" for a, vs in _W1_ITEMS.items() for v in vs) + " FROM t")
def bitmap_wide(spark, sf_dir):
    df, dic, _ = _w1_dense(spark, sf_dir)
    return items.bitmap_wide(df, dic, ["tid"])


@query(f"WITH {O.dense()} SELECT tid, label FROM long")
def bitmap_long(spark, sf_dir):
    df, dic, _ = _w1_dense(spark, sf_dir)
    return _labelled(items.bitmap_long(df, dic), dic).select("tid", "label")


def _labelled(df: DataFrame, dic: items.ItemDict) -> DataFrame:
    names = _frame(df.sparkSession, [(i, dic.label(i)) for i in range(len(dic.items))], "item_id int, label string")
    return df.join(F.broadcast(names), "item_id").drop("item_id")  # a row per item


@query(f"WITH {O.dense()} SELECT tid, {', '.join(O.ATTRIBUTES['w1'])} FROM t")
def decode_roundtrip(spark, sf_dir):
    df, dic, _ = _w1_dense(spark, sf_dir)
    return items.decode(items.bitmap_long(df, dic), dic)


@query("SELECT l_orderkey, l_linenumber, CASE WHEN l_quantity <= 16 THEN 'lo' WHEN l_quantity <= 33 THEN 'mid' ELSE 'hi' END AS qty, year(l_shipdate)::INTEGER AS y, month(l_shipdate)::INTEGER AS m FROM lineitem")
def band_explicit(spark, sf_dir):
    qty = discretize.band("l_quantity", *W.QUANTITY, closed="right")
    return load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", qty.alias("qty"), discretize.date_part("l_shipdate", "year").alias("y"), discretize.date_part("l_shipdate", "month").alias("m"))


@query("""WITH b AS (SELECT min(p_retailprice) AS lo, max(p_retailprice) AS hi FROM part)
    SELECT p_partkey, CASE WHEN p_retailprice < lo + (hi - lo) * 1 / 4 THEN 'b0' WHEN p_retailprice < lo + (hi - lo) * 2 / 4 THEN 'b1'
           WHEN p_retailprice < lo + (hi - lo) * 3 / 4 THEN 'b2' ELSE 'b3' END AS price FROM part, b""")
def band_width(spark, sf_dir):
    part = load(spark, sf_dir, "part").select("p_partkey", "p_retailprice")
    return part.select("p_partkey", discretize.band_width(part, "p_retailprice", 4).alias("price"))


@query("""WITH q AS (SELECT quantile_cont(c_acctbal, 0.25) AS a, quantile_cont(c_acctbal, 0.5) AS b, quantile_cont(c_acctbal, 0.75) AS c FROM customer)
    SELECT c_custkey, CASE WHEN c_acctbal < a THEN 'b0' WHEN c_acctbal < b THEN 'b1' WHEN c_acctbal < c THEN 'b2' ELSE 'b3' END AS bal FROM customer, q""")
def band_freq_exact(spark, sf_dir):
    customer = load(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")
    return customer.select("c_custkey", discretize.band_freq(customer, "c_acctbal", 4, exact=True).alias("bal"))


@query(f"SELECT {', '.join(O.ATTRIBUTES['w1'])}, count(*) AS weight FROM ({O.RELATIONS['w1']}) GROUP BY ALL")
def compact_rows(spark, sf_dir):
    info = W.w1(spark, sf_dir)
    return items.compact(info.df, info.attributes)


def _slots_sql(n: str, step: int = 1, least: int = 16) -> str:
    """The least power of 2^step that is n and `least` at least, found among all powers."""
    return f"list_min(list_filter([{', '.join(str(1 << i) for i in range(0, 62, step))}], lambda s: s >= greatest({n}, {least})))"


@query(f"""SELECT l_partkey, n, {_slots_sql('n')} AS pow2, {_slots_sql('n', step=2)} AS pow4, {_slots_sql('n + 1')} AS strict
    FROM (SELECT l_partkey, count(*) AS n FROM lineitem GROUP BY ALL)""")
def padded_sizes(spark, sf_dir):
    """Slots of a tree over each part's order lines, by the three rules of padding."""
    n = F.col("n")
    sizes = load(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n"))
    return sizes.select("l_partkey", "n", padded_slots(n).alias("pow2"), padded_slots(n, pad="pow4").alias("pow4"), padded_slots(n, pad_exact=True).alias("strict"))


@query(f"SELECT o_custkey, n, {_slots_sql('n')} AS slots FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY ALL)")
def padded_size_sql(spark, sf_dir):
    """Slots of a tree over each customer's orders, by the SQL function."""
    register_sql(spark)
    return spark.sql("SELECT o_custkey, count(*) AS n, padded_size(count(*)) AS slots FROM {orders} GROUP BY o_custkey", orders=load(spark, sf_dir, "orders").select("o_custkey"))


@query("""WITH t AS (SELECT i::INTEGER AS code, (i >> 2 & 1)::INTEGER AS a1, (i >> 1 & 1)::INTEGER AS a2, (i & 1)::INTEGER AS a3 FROM range(8) t(i)),
    c AS (SELECT CASE WHEN l_returnflag = 'R' THEN 4 ELSE 0 END + CASE WHEN l_linestatus = 'O' THEN 2 ELSE 0 END + CASE WHEN l_quantity > 33 THEN 1 ELSE 0 END AS code, count(*) AS cnt FROM lineitem GROUP BY ALL)
    SELECT t.*, coalesce(cnt, 0) AS cnt FROM t LEFT JOIN c ON t.code = c.code""")
def truth_table(spark, sf_dir):
    """All lines of the truth table of three items, returned, open and many pieces, and how many order lines are of each: none, too."""
    held = (F.col("l_returnflag") == "R", F.col("l_linestatus") == "O", F.col("l_quantity") > 33)
    t = tables.truth_table(spark, len(held))
    bits = [items.encode_binary(c)[0].alias(a) for c, a in zip(held, t.columns, strict=True)]
    counts = load(spark, sf_dir, "lineitem").select(*bits).groupBy(*t.columns).agg(F.count("*").alias("cnt"))
    code = (F.col("a1") * 4 + F.col("a2") * 2 + F.col("a3")).alias("code")
    return t.join(counts, t.columns, "left").select(code, *t.columns, F.coalesce("cnt", F.lit(0).cast("long")).alias("cnt"))


# Trees, over all items of all order lines.

_TREE = f"""{O.dense()},
    cap AS (SELECT CAST(pow(2, ceil(log2(greatest(count(*), 16)))) AS BIGINT) AS cap FROM t),
    lv AS (SELECT CAST(i AS INTEGER) AS level, greatest(1, cap >> (2 * i)) AS size, greatest(1, cap >> (2 * greatest(i - 1, 0))) AS above
           FROM cap, range(40) r(i) WHERE i = 0 OR cap >> (2 * greatest(i, 1) - 2) > 1),
    nodes AS (SELECT label, level, tid // size AS node_id, tid // above AS parent_id, size, count(*) AS cnt FROM long, lv GROUP BY ALL),
    pruned AS (SELECT c.* FROM nodes c LEFT JOIN nodes p ON p.label = c.label AND p.level = c.level - 1 AND p.node_id = c.parent_id
               WHERE p.cnt IS NULL OR p.cnt < p.size)"""


def _tree(spark, sf_dir):
    df, dic, _ = _w1_dense(spark, sf_dir)
    return items.bitmap_long(df, dic), dic, ptree.TreeShape.for_tuples(df.count())


def _pruned(spark, sf_dir):
    long, dic, shape = _tree(spark, sf_dir)
    return ptree.build_count_tree(long, shape, pruned=True), dic, shape


_NODE = ("label", "level", "node_id", "size", "cnt")


@query(f"WITH {O.dense()} SELECT label, count(*) AS cnt FROM long GROUP BY ALL")
def root_counts(spark, sf_dir):
    """From the headers of segments, which no order of tuples is needed for."""
    info = W.w1(spark, sf_dir)
    dic = items.build_items(info)
    heads = anding.segment_items(segment_trees.build_segment_trees(info.df, dic))
    return _labelled(heads.groupBy("item_id").agg(F.sum("root_cnt").alias("cnt")), dic)


@query(f"WITH {_TREE} SELECT label, node_id AS quadrant, cnt FROM nodes WHERE level = 1")
def quadrant_counts(spark, sf_dir):
    long, dic, shape = _tree(spark, sf_dir)
    return _labelled(ptree.quadrant_counts(long, shape), dic)


@query(f"WITH {_TREE} SELECT label, level, node_id, size, cnt FROM nodes WHERE size > 1")
def count_tree_levels(spark, sf_dir):
    long, dic, shape = _tree(spark, sf_dir)
    return _labelled(ptree.build_count_tree(long, shape), dic).where("size > 1").select(*_NODE)


@query(f"WITH {_TREE} SELECT label, level, node_id, size, cnt FROM pruned")
def pure_pruned_tree(spark, sf_dir):
    nodes, dic, _ = _pruned(spark, sf_dir)
    return _labelled(nodes, dic).select(*_NODE)


def _full(spark, sf_dir):
    """The tree with its pure-0 nodes."""
    nodes, dic, shape = _pruned(spark, sf_dir)
    return ptree.with_absent_children(tables.written(nodes, "tree"), shape), dic


_FULL = f"""{_TREE},
    kids AS (SELECT p.label, l.level, unnest(range(p.node_id * p.size // l.size, (p.node_id + 1) * p.size // l.size)) AS node_id, l.size
             FROM pruned p JOIN lv l ON l.level = p.level + 1 WHERE p.cnt < p.size),
    whole AS (SELECT label, level, node_id, size, cnt FROM pruned UNION ALL
              SELECT k.label, k.level, k.node_id, k.size, 0 FROM kids k LEFT JOIN nodes n USING (label, level, node_id) WHERE n.cnt IS NULL)"""


def _digest(nodes: DataFrame, dic: items.ItemDict, value: str) -> DataFrame:
    """Nodes by item, level and value: how many, and the sum of their ids and of their squares."""
    x = F.col("node_id").cast("decimal(38,0)")
    return _labelled(nodes, dic).groupBy("label", "level", value).agg(F.count("*").alias("nodes"), F.sum("node_id").alias("ids"), F.sum(x * x).cast("string").alias("squares"))


def _digest_sql(value: str, name: str) -> str:
    return f"WITH {_FULL} SELECT label, level, {value} AS {name}, count(*) AS nodes, CAST(sum(node_id) AS BIGINT) AS ids, CAST(sum(CAST(node_id AS HUGEINT) * node_id) AS VARCHAR) AS squares FROM whole GROUP BY ALL"


@query(_digest_sql("CASE WHEN cnt = size THEN '1' WHEN cnt = 0 THEN '0' ELSE 'm' END", "mask"))
def mask_tree(spark, sf_dir):
    nodes, dic = _full(spark, sf_dir)
    return _digest(ptree.to_mask_tree(nodes), dic, "mask")


@query(_digest_sql("cnt = size", "bit"))
def p1_tree(spark, sf_dir):
    nodes, dic = _full(spark, sf_dir)
    return _digest(ptree.to_p1(nodes), dic, "bit")


@query(_digest_sql("cnt = 0", "bit"))
def p0_tree(spark, sf_dir):
    nodes, dic = _full(spark, sf_dir)
    return _digest(ptree.to_p0(nodes), dic, "bit")


@query(f"WITH {O.dense()} SELECT tid, label FROM long")
def tree_expand(spark, sf_dir):
    nodes, dic, shape = _pruned(spark, sf_dir)
    path = f"{tables.shared_dir(spark)}/stored-{uuid.uuid4().hex}"
    ptree.store_trees(nodes, path, shape)
    return _labelled(ptree.expand_tree(ptree.load_trees(spark, path)), dic).select("tid", "label")


@query(f"WITH {O.dense()} SELECT label, count(*) AS cnt FROM long WHERE tid >= 1000 AND tid < 4321 GROUP BY ALL")
def range_count(spark, sf_dir):
    nodes, dic, _ = _pruned(spark, sf_dir)
    return _labelled(ptree.range_count(nodes, 1000, 4321), dic)


@query(f"WITH {O.dense()} SELECT label, tid // 64 AS word_id, count(*) AS ones FROM long GROUP BY ALL")
def word_popcounts(spark, sf_dir):
    df, dic, _ = _w1_dense(spark, sf_dir)
    words = ptree.build_words(items.bitmap_long(df, dic))
    return _labelled(words, dic).select("label", "word_id", F.bit_count("bits").cast("long").alias("ones"))


@query(f"""WITH {_TREE} SELECT label, level, count(*) AS nodes, count(*) FILTER (WHERE cnt = size) AS pure1, CAST(sum(cnt) AS BIGINT) AS ones FROM pruned GROUP BY ALL""")
def tree_stats(spark, sf_dir):
    nodes, dic, _ = _pruned(spark, sf_dir)
    return _labelled(ptree.tree_stats(nodes), dic)


_Z = "((x & 1) + (y & 1) * 2 + (x & 2) * 2 + (y & 2) * 4 + (x & 4) * 4 + (y & 4) * 8)"


@query(f"""WITH e AS (SELECT vec_id, unnest(embedding) AS v, unnest(range(64)) AS i FROM embeddings),
    c AS (SELECT vec_id, v > 0 AS bit, i % 8 AS x, i // 8 AS y FROM e), codes AS (SELECT vec_id, {_Z} AS code FROM c WHERE bit)
    SELECT vec_id, CAST(code // 16 AS BIGINT) AS quadrant, count(*) AS ones FROM codes GROUP BY ALL""")
def morton_grid(spark, sf_dir):
    """Embeddings as 8 x 8 rasters of sign bits in Z-order: ones by quadrant."""
    cells = load(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "v")).where("v > 0")
    code = morton(F.col("i") % 8, F.floor(F.col("i") / 8), 3)
    return cells.select("vec_id", F.floor(code / 16).alias("quadrant")).groupBy("vec_id", "quadrant").agg(F.count("*").alias("ones"))


@query(f"""WITH c AS (SELECT DISTINCT user_id, hour(ts) // 3 AS x, dayofweek(ts) AS y FROM events WHERE ts IS NOT NULL), codes AS (SELECT user_id, {_Z} AS code FROM c)
    SELECT user_id, 0::INTEGER AS level, 0::BIGINT AS node_id, count(*) AS cnt FROM codes GROUP BY ALL
    UNION ALL SELECT user_id, 1 AS level, CAST(code // 16 AS BIGINT) AS node_id, count(*) AS cnt FROM codes GROUP BY ALL""")
def raster_tree(spark, sf_dir):
    """The root and quadrants of each user's 8 x 8 raster of the week: three hours by column, a day by row (Sunday's first, the
    eighth padded with zeros), a bit for a cell with events."""
    events = load(spark, sf_dir, "events").where("ts IS NOT NULL")
    code = morton(F.floor(discretize.date_part("ts", "hour") / 3), discretize.date_part("ts", "dayofweek") - 1, 3)
    nodes = ptree.build_count_tree(events.select(F.col("user_id").alias("item_id"), code.alias("tid")), ptree.TreeShape.of(64))
    return nodes.where("level < 2").select(F.col("item_id").alias("user_id"), "level", "node_id", "cnt")


@query()
def tree_stats_bytes(spark, sf_dir):
    """Bytes of the miner's trees against raw bits, for tuples as they come and sorted by all attributes (what likeness of
    neighbours is worth): no SQL, as sizes depend on the partitions."""
    out = None
    info = W.w1(spark, sf_dir)
    for order, df in (("as they come", info.df), ("sorted", info.df.repartitionByRange(*info.attributes).sortWithinPartitions(*info.attributes))):
        trees = Trees(W.InfoTable(df, info.conditions, info.decisions))
        row = segment_trees.stored_bytes(trees.store).select(F.lit(order).alias("tuples"), "*", measures.compression_ratio(F.col("stored"), F.col("n"), F.lit(len(trees.items.items))).alias("ratio"))
        out = row if out is None else out.unionByName(row)
    return out


# ANDing.

_PAIR = "CASE WHEN cnt1 = size THEN '1' WHEN cnt1 = 0 THEN '0' ELSE 'm' END AS x1, CASE WHEN cnt2 = size THEN '1' WHEN cnt2 = 0 THEN '0' ELSE 'm' END AS x2"


@query(f"""WITH t AS (SELECT o_orderkey AS tid, bool_or(o_orderstatus <> 'P') AS in1, bool_or(o_orderpriority < '3') AS in2 FROM orders GROUP BY ALL),
    cap AS (SELECT CAST(pow(2, ceil(log2(greatest(max(tid) + 1, 16)))) AS BIGINT) AS cap FROM t),
    lv AS (SELECT CAST(i AS INTEGER) AS level, cap >> (2 * i) AS size FROM cap, range(31) r(i) WHERE cap >> (2 * i) > 1),
    c AS (SELECT level, tid // size AS node_id, size, count(*) FILTER (WHERE in1) AS cnt1, count(*) FILTER (WHERE in2) AS cnt2 FROM t, lv GROUP BY ALL),
    m AS (SELECT level, node_id, size, {_PAIR} FROM c)
    SELECT *, CASE WHEN x1 = '0' OR x2 = '0' THEN '0' WHEN x1 = '1' THEN x2 WHEN x2 = '1' THEN x1 ELSE 'recurse' END AS result FROM m""")
def and_mask_table(spark, sf_dir):
    """The trees of two items over all orders, by order key: the masks of each inner node that holds an order, and of their AND.
    An order that is neither item's makes its nodes known, so that pairs of pure-0 nodes are there too."""
    orders = load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("tid"), "o_orderstatus", "o_orderpriority")
    one, two, there = F.when(F.col("o_orderstatus") != "P", 1), F.when(F.col("o_orderpriority") < "3", 2), F.lit(0)
    long = orders.select(F.explode(F.array_compact(F.array(there, one, two))).alias("item_id"), "tid")
    last = orders.agg(F.max("tid")).first()[0]
    masks = ptree.to_mask_tree(ptree.build_count_tree(long, ptree.TreeShape.for_tuples((last or 0) + 1)).where("size > 1"))
    x1, x2 = (F.coalesce(F.max(F.when(F.col("item_id") == i, F.col("mask"))), F.lit("0")) for i in (1, 2))
    pairs = masks.groupBy("level", "node_id", "size").agg(x1.alias("x1"), x2.alias("x2"))
    return pairs.withColumn("result", and_mask(F.col("x1"), F.col("x2")))


def _and(spark, sf_dir, names, labels, how):
    df, dic, _ = _w1_dense(spark, sf_dir)
    own = items.ItemDict(tuple(x for x in dic.items if x[0] in names))
    long = items.bitmap_long(df, own)
    number = {own.label(i): i for i in range(len(own.items))}
    cands = _frame(spark, [(i, sorted(number[x] for x in s)) for i, s in enumerate(labels)], "cand_id int, items array<int>")
    counts = how(long, cands)
    text = _frame(spark, [(i, "|".join(sorted(s))) for i, s in enumerate(labels)], "cand_id int, label string")
    return counts.join(F.broadcast(text), "cand_id").select("label", "cnt")


_TWO = [(f"rf={a}", f"class={b}") for a in "ANR" for b in ("c1", "c2", "c3", "c4")]
_THREE = [(f"rf={a}", f"ls={b}", f"qty={c}") for a in "ANR" for b in "FO" for c in ("lo", "mid", "hi")]


@query(f"SELECT 'class=' || class || '|rf=' || rf AS label, count(*) AS cnt FROM ({O.RELATIONS['w1']}) GROUP BY ALL")
def and_two_items(spark, sf_dir):
    return _and(spark, sf_dir, ("rf", "class"), _TWO, lambda long, c: anding.and_words(ptree.build_words(long), c))


_THREE_SQL = f"SELECT 'ls=' || ls || '|qty=' || qty || '|rf=' || rf AS label, count(*) AS cnt FROM ({O.RELATIONS['w1']}) GROUP BY ALL"


@query(_THREE_SQL)
def and_three_items(spark, sf_dir):
    return _and(spark, sf_dir, ("rf", "ls", "qty"), _THREE, lambda long, c: anding.and_words(ptree.build_words(long), c))


@query(_THREE_SQL)
def bitmap_and_agg_counts(spark, sf_dir):
    return _and(spark, sf_dir, ("rf", "ls", "qty"), _THREE, lambda long, c: anding.and_bitmaps(ptree.build_bitmaps(long), c))


@query(f"""WITH {_TREE}, own AS (SELECT tid FROM t WHERE os = 'F' AND class = 'c1'),
    met AS (SELECT level, tid // size AS node_id, tid // above AS parent_id, size, count(*) AS cnt FROM own, lv GROUP BY ALL)
    SELECT c.level, c.node_id, c.size, c.cnt FROM met c LEFT JOIN met p ON p.level = c.level - 1 AND p.node_id = c.parent_id WHERE p.cnt IS NULL OR p.cnt < p.size""")
def and_nodes_equals_words(spark, sf_dir):
    """The node-by-node AND of two trees."""
    nodes, dic, shape = _pruned(spark, sf_dir)
    pruned = tables.written(nodes, "tree")
    one, two = (pruned.where(F.col("item_id") == dic.items.index(x)).drop("item_id") for x in (("os", "F"), ("class", "c1")))
    return anding.and_trees(one, two, shape)


@query(f"""WITH e AS ({O.RELATIONS["w1"]}) SELECT 'not os=F' AS what, count(*) FILTER (WHERE os <> 'F') AS cnt FROM e
    UNION ALL SELECT 'os=F or os=P', count(*) FILTER (WHERE os IN ('F', 'P')) FROM e""")
def not_or_words(spark, sf_dir):
    df, dic, _ = _w1_dense(spark, sf_dir)
    words = ptree.build_words(items.bitmap_long(df, dic))
    f, p = (dic.items.index(("os", x)) for x in "FP")
    no = anding.not_words(words.where(F.col("item_id") == f), df.count()).agg(F.sum(F.bit_count("bits")).alias("cnt")).select(F.lit("not os=F").alias("what"), "cnt")
    either = anding.or_words(words.where(F.col("item_id").isin(f, p))).agg(F.sum(F.bit_count("bits")).alias("cnt")).select(F.lit("os=F or os=P").alias("what"), "cnt")
    return no.unionByName(either)


# Mining.


def _mined(spark, sf_dir, w, **how):
    s, c = W.THRESHOLDS[w]
    info = W.w4(spark) if w == "w4" else W.WORKLOADS[w](spark, sf_dir)
    return mine_ptree(info, s, c, **how)


def _rules(out) -> DataFrame:
    return out.rules.select(*R.COLUMNS)


def _sets(df: DataFrame) -> DataFrame:
    return df.select("k", "label", "cnt")


for _w in ("w1", "w2", "w3"):
    query(O.itemsets(_w), f"itemsets_{_w}")(lambda spark, sf_dir, w=_w: _sets(_mined(spark, sf_dir, w).itemsets))
    query(O.rules(_w), f"rules_free_{_w}")(lambda spark, sf_dir, w=_w: _rules(_mined(spark, sf_dir, w)))
    query(O.rules(_w, f"decision = '{O.DECISION[_w]}'"), f"rules_fixed_{_w}")(lambda spark, sf_dir, w=_w: _rules(_mined(spark, sf_dir, w, decision=O.DECISION[w])))
QUERIES["rules_single_w1"], ORACLE_SQL["rules_single_w1"] = QUERIES.pop("rules_free_w1"), ORACLE_SQL.pop("rules_free_w1")

query(O.itemsets("w1", "k = 1"), "frequent_1")(lambda spark, sf_dir: _frequent_1(spark, sf_dir))


def _frequent_1(spark, sf_dir):
    """From root counts alone."""
    from .functions.thresholds import min_count
    from .plans.results import itemset_frame

    trees = Trees(W.w1(spark, sf_dir))
    return _sets(itemset_frame(spark, frequent_items(trees.roots, min_count("0.10", trees.n)), trees.items))


def _grown(spark, sf_dir, k):
    """Level k from the DataFrame forms of the join, prune and AND."""
    from .functions.thresholds import min_count

    df, dic, _ = _w1_dense(spark, sf_dir)
    words = tables.written(ptree.build_words(items.bitmap_long(df, dic)), "words")
    least = min_count("0.10", df.count())
    one = ptree.root_counts(words).where(F.col("cnt") >= least)
    level = one.select(F.array("item_id").alias("items"), "cnt")
    attribute = dic.frame(spark).select("item_id", "attribute")
    for _ in range(k - 1):
        cands = candidates.next_level(level.select("items"), attribute).withColumn("cand_id", F.xxhash64("items"))
        cands = tables.written(cands, "candidates")
        level = tables.written(anding.and_words(words, cands).where(F.col("cnt") >= least).join(cands, "cand_id").select("items", "cnt"), "level")
    names = F.create_map(*[x for i in range(len(dic.items)) for x in (F.lit(i), F.lit(dic.label(i)))])
    text = F.array_join(F.array_sort(F.transform("items", lambda i: F.element_at(names, i))), "|")
    return level.select(F.size("items").alias("k"), text.alias("label"), "cnt")


query(O.itemsets("w1", "k = 2"), "frequent_2")(lambda spark, sf_dir: _grown(spark, sf_dir, 2))
query(O.itemsets("w1", "k = 3"), "frequent_3")(lambda spark, sf_dir: _grown(spark, sf_dir, 3))
query(O.itemsets("w1", strict=True), "itemsets_strict")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w1", strict=True).itemsets))
query(O.itemsets("w1", "len(list_filter(parts, lambda x: starts_with(x, 'class='))) = 1"), "fixed_itemsets_w1")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w1", decision="class").itemsets))
query(O.itemsets("w1"), "segmented_itemsets_w1")(lambda spark, sf_dir: _sets(mine_segmented(W.w1(spark, sf_dir), *W.THRESHOLDS["w1"], segment=4**6).itemsets))
query(O.itemsets("w1"), "itemsets_segments_w1")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w1", counting="segments").itemsets))
query(O.itemsets("w1"), "itemsets_bounded_w1")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w1", bound=True).itemsets))
query(O.rules("w1"), "strong_rules_by_level_w1")(lambda spark, sf_dir: _rules(_mined(spark, sf_dir, "w1", emit="strong")))
query(O.rules("w2", f"decision = '{O.DECISION['w2']}'"), "strong_rules_by_level_fixed_w2")(lambda spark, sf_dir: _rules(_mined(spark, sf_dir, "w2", decision=O.DECISION["w2"], emit="strong")))
query(O.itemsets("w1"), "itemsets_words_w1")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w1", counting="words").itemsets))
query(O.itemsets("w1"), "itemsets_no_reuse_w1")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w1", reuse="none").itemsets))
query(O.rules("w1", "decision IN ('class', 'os')"), "rules_several_decisions_w1")(lambda spark, sf_dir: _rules(_mined(spark, sf_dir, "w1", decision=["class", "os"])))


@query(O.itemsets("w1"))
def itemsets_incremental_w1(spark, sf_dir):
    """Trees of the lines with other statuses, then those of status F appended."""
    info = W.w1(spark, sf_dir)
    first = W.InfoTable(info.df.where("os != 'F'"), info.conditions, info.decisions)
    trees = append_segments(Trees(first, items=items.build_items(info)), info.df.where("os = 'F'"))
    return _sets(mine_ptree(info, *W.THRESHOLDS["w1"], trees=trees).itemsets)


# Rules.

query(O.rules_any("w1"), "rules_any_w1")(lambda spark, sf_dir: _mined(spark, sf_dir, "w1", consequent="any").rules.drop("decision", *R.SIDES))


@query(
    O.rules("w2", "decision = 'has_digit' AND NOT EXISTS (FROM r q WHERE q.consequent = r.consequent AND q.k < r.k AND q.cnt_xy * r.cnt_x >= r.cnt_xy * q.cnt_x AND list_has_all(string_split(r.antecedent, '|'), string_split(q.antecedent, '|')))")
)
def rules_nonredundant(spark, sf_dir):
    return _rules(_mined(spark, sf_dir, "w2", decision="has_digit", criterion="shorter_as_good"))


@query(O.rules("w2", "decision = 'has_digit' AND NOT EXISTS (FROM r q WHERE q.consequent = r.consequent AND q.k < r.k AND q.cnt_x = r.cnt_x AND list_has_all(string_split(r.antecedent, '|'), string_split(q.antecedent, '|')))"))
def rules_own_cover(spark, sf_dir):
    return _rules(_mined(spark, sf_dir, "w2", decision="has_digit", criterion="same_cover"))


@query(O.rules("w2", select="k, decision, count(*) AS rules", where="true GROUP BY k, decision"))
def rules_profile(spark, sf_dir):
    return measures.rule_profile(_mined(spark, sf_dir, "w2").rules)


@query(O.rules("w1", select="""antecedent, consequent, cnt_xy, round(CAST(cnt_xy AS DOUBLE) * n / (CAST(cnt_x AS DOUBLE) * y.cnt), 9) AS lift,
    round(CAST(cnt_xy AS DOUBLE) / n - (CAST(cnt_x AS DOUBLE) / n) * (CAST(y.cnt AS DOUBLE) / n), 9) AS leverage,
    round(CASE WHEN cnt_x <> cnt_xy THEN (CAST(cnt_x AS DOUBLE) * (n - y.cnt)) / (CAST(n AS DOUBLE) * (cnt_x - cnt_xy)) END, 9) AS conviction,
    round(CAST(cnt_xy AS DOUBLE) / (cnt_x + y.cnt - cnt_xy), 9) AS jaccard""").replace("FROM r WHERE", "FROM r JOIN f y ON y.label = consequent WHERE"))  # fmt: skip
def rule_lift(spark, sf_dir):
    out = _mined(spark, sf_dir, "w1")
    counts = out.itemsets.where("k = 1").select(F.col("label").alias("consequent"), F.col("cnt").alias("cnt_y"))
    shown = measures.interest(out.rules, counts)
    return shown.select("antecedent", "consequent", "cnt_xy", *(F.round(c, 9).alias(c) for c in ("lift", "leverage", "conviction", "jaccard")))


query(O.rules("w4"), "worked_example_rules")(lambda spark, sf_dir: _rules(_mined(spark, sf_dir, "w4")))
query(O.itemsets("w4"), "worked_example_itemsets")(lambda spark, sf_dir: _sets(_mined(spark, sf_dir, "w4").itemsets))
query(O.rules("w4", "decision = 'F' AND NOT contains(antecedent, 'G=')"), "worked_example_decision_f")(lambda spark, sf_dir: _rules(_mined(spark, sf_dir, "w4", decision="F", conditions=list("ABCDE"))))


@query(O.rules("w4", select="k, " + ", ".join(f"coalesce(array_to_string(list_sort(list(antecedent || ' -> ' || consequent) FILTER (WHERE decision = '{d}')), '; '), '') AS \"{d}\"" for d in "FG"), where="decision IN ('F', 'G') GROUP BY k"))
def worked_example_table(spark, sf_dir):
    """Strong rules by antecedent size and decision attribute."""
    return R.rules_table(_mined(spark, sf_dir, "w4", decision=["F", "G"]).rules)


_ROW = ", ".join(f"'{a}=' || {a}" for a in O.ATTRIBUTES["w1"])


@query(O.rules("w1", "true", more=f""", r2 AS (SELECT antecedent, consequent, CAST(cnt_xy AS DOUBLE) / cnt_x AS confidence, CAST(cnt_xy AS DOUBLE) / n AS support FROM r WHERE decision = 'class'),
    row_items AS (SELECT {', '.join(O.ATTRIBUTES['w1'])}, weight, [{_ROW}] AS parts FROM c),
    hit AS (SELECT c.*, r2.consequent, row_number() OVER (PARTITION BY {', '.join('c.' + a for a in O.ATTRIBUTES['w1'])} ORDER BY confidence DESC NULLS LAST, support DESC, antecedent DESC, consequent DESC) AS o
            FROM row_items c LEFT JOIN r2 ON list_has_all(c.parts, string_split(r2.antecedent, '|')))""", select="class, consequent AS conclusion, CAST(sum(weight) AS BIGINT) AS cnt").replace("FROM r WHERE true", "FROM hit WHERE o = 1 GROUP BY class, consequent"))  # fmt: skip
def rules_applied(spark, sf_dir):
    """Each order line's class as its best rule concludes it, against the true one."""
    out = _mined(spark, sf_dir, "w1", decision="class")
    info = W.w1(spark, sf_dir)
    rows = items.compact(info.df, info.attributes)
    got = R.apply_rules(rows, out.rules, items.item_array(out.items))
    return got.groupBy("class", "conclusion").agg(F.sum("weight").alias("cnt"))


@query(O.rules("w1", select="decision, antecedent, consequent, CAST(rank AS INTEGER) AS rank FROM (SELECT *, rank() OVER (PARTITION BY decision ORDER BY CAST(cnt_xy AS DOUBLE) / cnt_x DESC, cnt_xy DESC, antecedent) AS rank FROM r) WHERE rank <= 3 --"))
def topk_rules(spark, sf_dir):
    order = Window.partitionBy("decision").orderBy(F.desc("confidence"), F.desc("cnt_xy"), "antecedent")
    ranked = _mined(spark, sf_dir, "w1").rules.withColumn("rank", F.rank().over(order))
    return ranked.where("rank <= 3").select("decision", "antecedent", "consequent", "rank")


# Baselines.

query(O.rules("w1"), "apriori_w1")(lambda spark, sf_dir: _rules(baselines.mine_apriori(W.w1(spark, sf_dir), *W.THRESHOLDS["w1"])))
query(O.rules("w1", "decision = 'class'"), "hybrid_w1")(lambda spark, sf_dir: _rules(baselines.mine_hybrid(W.w1(spark, sf_dir), *W.THRESHOLDS["w1"], decision="class")))
query(O.rules("w1", "decision = 'class'"), "rough_set_w1")(lambda spark, sf_dir: _rules(baselines.mine_rough_set(W.w1(spark, sf_dir), *W.THRESHOLDS["w1"], decision="class")))
query(O.rules("w1"), "rough_set_free_w1")(lambda spark, sf_dir: _rules(baselines.mine_rough_set(W.w1(spark, sf_dir), *W.THRESHOLDS["w1"])))
query(O.rules("w1"), "brute_force_w1")(lambda spark, sf_dir: _rules(baselines.mine_brute_force(W.w1(spark, sf_dir), *W.THRESHOLDS["w1"])))
query(O.itemsets("w1"), "fpgrowth_w1")(lambda spark, sf_dir: baselines.mine_fpgrowth(W.w1(spark, sf_dir), "0.10"))


#: The enumerating generator takes too long on W3's rows, which hardly ever agree; its cells there are the bench's.
_COMPARED = {"w1": ("ptree", "apriori", "hybrid", "rough_set"), "w2": ("ptree", "apriori", "hybrid", "rough_set"), "w3": ("ptree", "apriori", "hybrid")}


def _no_difference(w: str) -> str:
    cells = [(mode, m) for mode in ("fixed", "free") for m in _COMPARED[w][1:] if (m, mode) != ("apriori", "fixed")]
    return "SELECT * FROM (VALUES " + ", ".join(f"('{mode}', '{m}', 0::BIGINT)" for mode, m in cells) + ") t(mode, method, differing)"


for _w, _name in (("w1", "rule_diff_methods"), ("w2", "rule_diff_methods_w2"), ("w3", "rule_diff_methods_w3")):
    query(_no_difference(_w), _name)(lambda spark, sf_dir, w=_w: _differences(spark, sf_dir, w))


def _differences(spark, sf_dir, w):
    """Rules that the tree miner and a baseline don't share, by mode: none."""
    rows = [(mode, m, n) for mode in ("fixed", "free") for m, n in grid.differences(spark, sf_dir, w, mode, _COMPARED[w]).items()]
    return _frame(spark, rows, "mode string, method string, differing long")


@query()
def method_timings(spark, sf_dir):
    """Minutes (wall and CPU) of every cell of the comparison on the first data set, and the factor over the tree miner."""
    info = grid.prepared(spark, sf_dir, "w1")
    rows = [(d, mode, m, n, t.wall, t.cpu) for d, mode, m in grid.cells(("w1",)) for n, t in [grid.time_cell(info, d, mode, m)]]
    timed = _frame(spark, rows, "dataset string, mode string, method string, rules int, minutes double, cpu double")
    return timed.join(measures.speedup(timed).select("dataset", "mode", "method", "times"), ["dataset", "mode", "method"])


_SUPPORTS = (5, 10, 15, 20, 25, 30, 35)


@query(f"""WITH {O.counted("w1", percent=min(_SUPPORTS))}, p AS (SELECT unnest({list(_SUPPORTS)}) AS percent),
    fp AS (SELECT percent, label, cnt, parts, k FROM f, n, p WHERE cnt * 100 >= percent * n),
    s AS (SELECT percent, array_to_string(list_filter(parts, lambda x: x <> y), '|') AS antecedent, cnt FROM (SELECT percent, parts, cnt, unnest(parts) AS y FROM fp WHERE k > 1)),
    r AS (SELECT s.percent, count(*) AS rules FROM s JOIN fp ON s.percent = fp.percent AND s.antecedent = fp.label WHERE s.cnt * 100 >= 75 * fp.cnt GROUP BY ALL)
    SELECT percent, itemsets, coalesce(rules, 0) AS rules FROM (SELECT percent, count(*) AS itemsets FROM fp GROUP BY ALL) LEFT JOIN r USING (percent)""")
def minsup_sweep_w1(spark, sf_dir):
    """Itemsets and strong rules of the tree miner as the support goes from 5 to 35 %, on trees built once."""
    found = grid.minsup_sweep(W.w1(spark, sf_dir), [f"{p / 100}" for p in _SUPPORTS], "0.75")
    return _frame(spark, [(p, f[1], f[2]) for p, f in zip(_SUPPORTS, found, strict=True)], "percent int, itemsets long, rules long")


@query(f"""WITH {O.counted("w1")}, u AS (SELECT DISTINCT list_sort(list_distinct(list_concat(a.parts, b.parts))) AS u, a.k + 1 AS k FROM f a JOIN f b ON a.k = b.k AND a.label < b.label),
    made AS (SELECT u, k FROM u WHERE len(u) = k AND len(list_distinct(list_transform(u, lambda x: split_part(x, '=', 1)))) = k),
    whole AS (SELECT made.u, made.k FROM made JOIN f s ON s.k = made.k - 1 AND list_has_all(made.u, s.parts) GROUP BY ALL HAVING count(*) = made.k)
    SELECT CAST(k AS INTEGER) AS k, candidates, coalesce(frequent, 0) AS frequent FROM (
        SELECT 1 AS k, CAST(sum(n) AS BIGINT) AS candidates FROM ({" UNION ALL ".join(f"SELECT count(DISTINCT {a}) AS n FROM c" for a in O.ATTRIBUTES["w1"])})
        UNION ALL SELECT k, count(*) FROM whole GROUP BY k) LEFT JOIN (SELECT k, count(*) AS frequent FROM f GROUP BY k) USING (k)""")
def level_counts_w1(spark, sf_dir):
    """Candidates after the prune step and frequent sets of every level."""
    return _mined(spark, sf_dir, "w1").stats.frame(spark).select("k", "candidates", "frequent")


@query()
def level_ands_w1(spark, sf_dir):
    """What every level did: candidates, those pruned and bounded, blocks ANDed and spared by the trees, scans of the relation
    (one for all levels). No SQL, as ANDs depend on the partitions."""
    info = W.w1(spark, sf_dir)
    sorted_ = W.InfoTable(info.df.repartitionByRange(*info.attributes).sortWithinPartitions(*info.attributes), info.conditions, info.decisions)
    out = [mine_ptree(t, *W.THRESHOLDS["w1"], bound=b).stats.frame(spark).withColumn("tuples", F.lit(name)) for name, t, b in (("as they come", info, False), ("sorted", sorted_, True))]
    return out[0].unionByName(out[1])


# The relational surface.


@query("SELECT o_orderpriority, count(*) AS cnt, sum(l_quantity) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity BETWEEN 5 AND 30 GROUP BY ALL")
def join_inner(spark, sf_dir):
    lines = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_quantity between 5 and 30").select("l_orderkey", "l_quantity")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    return lines.join(orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("cnt"), F.sum("l_quantity").alias("qty"))


@query("SELECT d.doc_id, lang, quality, toxic, quality IS NULL AS unlabelled FROM documents d LEFT JOIN labels USING (doc_id)")
def join_left(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", "lang")
    return docs.join(load(spark, sf_dir, "labels"), "doc_id", "left").select("doc_id", "lang", "quality", "toxic", F.col("quality").isNull().alias("unlabelled"))


@query("SELECT c_custkey, s_suppkey FROM (SELECT * FROM customer WHERE c_acctbal > 9000) FULL JOIN (SELECT * FROM supplier WHERE s_acctbal > 0) ON c_custkey = s_suppkey")
def join_full(spark, sf_dir):
    c = load(spark, sf_dir, "customer").where("c_acctbal > 9000").select("c_custkey")
    s = load(spark, sf_dir, "supplier").where("s_acctbal > 0").select("s_suppkey")
    return c.join(s, F.col("c_custkey") == F.col("s_suppkey"), "full")


@query("SELECT o_orderkey, o_orderstatus FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R')")
def join_semi(spark, sf_dir):
    back = load(spark, sf_dir, "lineitem").where("l_returnflag = 'R'").select("l_orderkey")
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus").join(back, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")


@query("SELECT o_orderkey, o_orderstatus FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(spark, sf_dir):
    lines = load(spark, sf_dir, "lineitem").select("l_orderkey")
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left_anti")


@query("SELECT c_custkey, lo FROM customer JOIN (VALUES (-1000::DOUBLE, 0::DOUBLE), (0, 2500), (2500, 6000), (6000, 1e9)) b(lo, hi) ON c_acctbal >= lo AND c_acctbal < hi")
def join_range(spark, sf_dir):
    bands = _frame(spark, [(-1000.0, 0.0), (0.0, 2500.0), (2500.0, 6000.0), (6000.0, 1e9)], "lo double, hi double")
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_acctbal")
    return c.join(F.broadcast(bands), (F.col("c_acctbal") >= F.col("lo")) & (F.col("c_acctbal") < F.col("hi"))).select("c_custkey", "lo")


@query("""SELECT e.event_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts < e.ts OR p.ts = e.ts AND p.event_id < e.event_id)) AS previous FROM events e""")
def join_asof(spark, sf_dir):
    """Each event with the user's last purchase before it: one window pass, no pairs."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    hit = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return load(spark, sf_dir, "events").select("event_id", F.last(hit, ignorenulls=True).over(order).alias("previous"))


_CUBE = "SELECT rf, os, class, count(*) AS cnt, CAST(grouping(rf) * 4 + grouping(os) * 2 + grouping(class) AS BIGINT) AS gid FROM ({0}) GROUP BY {1}"


@query(_CUBE.format(O.RELATIONS["w1"], "CUBE (rf, os, class)"))
def cube_counts(spark, sf_dir):
    return W.w1(spark, sf_dir).df.cube("rf", "os", "class").agg(F.count("*").alias("cnt"), F.grouping_id().alias("gid"))


@query(_CUBE.format(O.RELATIONS["w1"], "ROLLUP (rf, os, class)"))
def rollup_counts(spark, sf_dir):
    return W.w1(spark, sf_dir).df.rollup("rf", "os", "class").agg(F.count("*").alias("cnt"), F.grouping_id().alias("gid"))


@query(_CUBE.format(O.RELATIONS["w1"], "GROUPING SETS ((rf, class), (os, class), (class))"))
def grouping_sets_counts(spark, sf_dir):
    sets = [[F.col("rf"), F.col("class")], [F.col("os"), F.col("class")], [F.col("class")]]
    return W.w1(spark, sf_dir).df.groupingSets(sets, "rf", "os", "class").agg(F.count("*").alias("cnt"), F.grouping_id().alias("gid"))


@query(f"SELECT oy, count(*) FILTER (WHERE class = 'c1') AS c1, count(*) FILTER (WHERE class = 'c2') AS c2, count(*) FILTER (WHERE class = 'c3') AS c3, count(*) FILTER (WHERE class = 'c4') AS c4 FROM ({O.RELATIONS['w1']}) GROUP BY oy")
def pivot_counts(spark, sf_dir):
    return W.w1(spark, sf_dir).df.groupBy("oy").pivot("class", ["c1", "c2", "c3", "c4"]).agg(F.count(F.lit(1))).na.fill(0)


@query("SELECT c_custkey, 'bal' AS what, c_acctbal AS v FROM customer UNION ALL SELECT c_custkey, 'nation', CAST(c_nationkey AS DOUBLE) FROM customer")
def unpivot_values(spark, sf_dir):
    c = load(spark, sf_dir, "customer").select("c_custkey", F.col("c_acctbal").alias("bal"), F.col("c_nationkey").cast("double").alias("nation"))
    return c.unpivot("c_custkey", ["bal", "nation"], "what", "v")


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(*) FILTER (WHERE l_quantity > 25) AS many, bit_xor(l_linenumber) AS x FROM lineitem GROUP BY ALL")
def agg_distinct(spark, sf_dir):
    lines = load(spark, sf_dir, "lineitem")
    return lines.groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_if(F.col("l_quantity") > 25).alias("many"), F.bit_xor("l_linenumber").alias("x"))


@query("SELECT l_orderkey, array_to_string(list_sort(list_distinct(list('type=' || p_type) || list('brand=' || p_brand))), '|') AS labels FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL")
def market_baskets(spark, sf_dir):
    return W.baskets(spark, sf_dir).select("l_orderkey", F.array_join("labels", "|").alias("labels"))


@query("""WITH b AS (SELECT DISTINCT l_orderkey, unnest(['type=' || p_type, 'brand=' || p_brand]) AS i FROM lineitem JOIN part ON l_partkey = p_partkey),
    n AS (SELECT count(DISTINCT l_orderkey) AS n FROM b), s AS (SELECT i, count(*) AS c FROM b GROUP BY i),
    p AS (SELECT a.i AS x, b.i AS y, count(*) AS cnt_xy FROM b a JOIN b USING (l_orderkey) WHERE a.i <> b.i GROUP BY ALL)
    SELECT x AS antecedent, y AS consequent, cnt_xy, c AS cnt_x, n FROM p JOIN s ON s.i = x, n WHERE cnt_xy * 100 >= 5 * n AND cnt_xy * 100 >= 30 * c""")
def basket_rules(spark, sf_dir):
    """Rules between two labels of an order at 5 % and 30 %: sparse two-valued items, by pairs within an order's small set."""
    b = W.baskets(spark, sf_dir)
    n = b.count()
    single = b.select(F.explode("labels").alias("antecedent")).groupBy("antecedent").agg(F.count("*").alias("cnt_x"))
    pairs = b.select(F.explode("labels").alias("antecedent"), "labels").select("antecedent", F.explode("labels").alias("consequent")).where("antecedent != consequent")
    both = pairs.groupBy("antecedent", "consequent").agg(F.count("*").alias("cnt_xy")).where(F.col("cnt_xy") * 100 >= 5 * n)
    return both.join(single, "antecedent").where("cnt_xy * 100 >= 30 * cnt_x").select("antecedent", "consequent", "cnt_xy", "cnt_x", F.lit(n).cast("long").alias("n"))


@query("SELECT p_partkey, CAST(rank() OVER w AS INTEGER) AS r, CAST(dense_rank() OVER w AS INTEGER) AS d, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS INTEGER) AS q FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice)")
def window_rank(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy("p_retailprice")
    full = Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")
    return load(spark, sf_dir, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(full).alias("q"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW) AS last4, lag(event_type) OVER u AS before, lead(event_type) OVER u AS after FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_frame(spark, sf_dir):
    u = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return load(spark, sf_dir, "events").select("event_id", F.count("*").over(u.rowsBetween(-3, 0)).alias("last4"), F.lag("event_type").over(u).alias("before"), F.lead("event_type").over(u).alias("after"))


_NATIONS = "SELECT c_nationkey AS k FROM customer WHERE c_acctbal > 0 {0} SELECT s_nationkey AS k FROM supplier"


def _sides(spark, sf_dir):
    return load(spark, sf_dir, "customer").where("c_acctbal > 0").select(F.col("c_nationkey").alias("k")), load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("k"))


for _name, _sql, _op in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_intersect", "INTERSECT ALL", DataFrame.intersectAll), ("set_except", "EXCEPT ALL", DataFrame.exceptAll)):
    query(_NATIONS.format(_sql), _name)(lambda spark, sf_dir, op=_op: op(*_sides(spark, sf_dir)))


@query("SELECT event_type, CAST(json_extract(props, '$.k') AS INTEGER) % 10 AS k, count(*) AS cnt FROM events GROUP BY ALL")
def json_props(spark, sf_dir):
    k = F.from_json("props", "k int").k
    return load(spark, sf_dir, "events").groupBy("event_type", (k % 10).alias("k")).agg(F.count("*").alias("cnt"))


@query("SELECT p_partkey, lower(trim(p_name)) AS name, split_part(p_brand, '#', 2) AS brand, regexp_extract(p_brand, '([0-9]+)', 1) AS digits, concat_ws('=', 'type', p_type) AS label FROM part")
def string_fns(spark, sf_dir):
    return load(spark, sf_dir, "part").select("p_partkey", F.lower(F.trim("p_name")).alias("name"), F.split_part("p_brand", F.lit("#"), F.lit(2)).alias("brand"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"), F.concat_ws("=", F.lit("type"), "p_type").alias("label"))


@query("SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(dayofweek(o_orderdate) + 1 AS INTEGER) AS d, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
def date_fns(spark, sf_dir):
    at = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.year(at).alias("y"), F.month(at).alias("m"), F.dayofweek(at).alias("d"), F.datediff(at.cast("date"), F.lit("1995-01-01").cast("date")).alias("days"))


@query("SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, CAST(len(embedding) AS INTEGER) AS n, list_max(embedding) AS top FROM embeddings")
def array_fns(spark, sf_dir):
    return load(spark, sf_dir, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.size("embedding").alias("n"), F.array_max("embedding").alias("top"))


@query("SELECT user_id, count(*) FILTER (WHERE event_type = 'purchase') AS purchases, CAST(count(DISTINCT event_type) AS INTEGER) AS kinds FROM events GROUP BY ALL")
def map_fns(spark, sf_dir):
    counts = load(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.try_element_at("m", F.lit("purchase")), F.lit(0).cast("long")).alias("purchases"), F.size(F.map_keys("m")).alias("kinds"))


@query("SELECT p_partkey, p_type, p_size, p_retailprice FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 25")
def topk_parts(spark, sf_dir):
    return load(spark, sf_dir, "part").select("p_partkey", "p_type", "p_size", "p_retailprice").orderBy(F.desc("p_retailprice"), "p_partkey").limit(25)


@query("SELECT p_partkey, p_name, p_brand, p_size FROM part UNION ALL SELECT p_partkey, p_name, p_brand, p_size FROM part UNION ALL SELECT p_partkey, p_name, p_brand, p_size FROM part")
def format_round_trips(spark, sf_dir):
    """part through CSV, JSON and ORC."""
    part = load(spark, sf_dir, "part").select("p_partkey", "p_name", "p_brand", "p_size")
    return reduce(DataFrame.unionByName, [tables.round_trip(part, f) for f in ("csv", "json", "orc")])


@query("WITH big AS (SELECT c_nationkey FROM customer GROUP BY 1 HAVING count(*) > (SELECT count(*) / 25.0 FROM customer)) SELECT n_name, n_regionkey FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM big)")
def subqueries(spark, sf_dir):
    tables.register_views(spark, sf_dir)
    return spark.sql("WITH big AS (SELECT c_nationkey FROM customer GROUP BY 1 HAVING count(*) > (SELECT count(*) / 25.0 FROM customer)) SELECT n_name, n_regionkey FROM nation WHERE n_nationkey IN (SELECT c_nationkey FROM big)")


@query(O.rules("w1", select="consequent, count(*) AS rules, max(CAST(cnt_xy AS DOUBLE) / cnt_x) AS best", where="true GROUP BY consequent"))
def rules_in_sql(spark, sf_dir):
    """Rules as a view."""
    _mined(spark, sf_dir, "w1").rules.createOrReplaceTempView("mined_rules")
    return spark.sql("SELECT consequent, count(*) AS rules, max(confidence) AS best FROM mined_rules GROUP BY consequent")


# Time.

_BAND = "CASE WHEN value < 25 THEN 'lo' WHEN value < 75 THEN 'mid' ELSE 'hi' END"
_UTC = "CAST({0} AS TIMESTAMP)"


def _plain(df: DataFrame, *names: str) -> DataFrame:
    """Times as whole seconds, which no zone setting changes."""
    return df.select(*(F.col(c).cast("long").alias(c) if c in names else c for c in df.columns))


@query("SELECT CAST(epoch(time_bucket(INTERVAL 1 DAY, CAST(ts AS TIMESTAMP), TIMESTAMP '1970-01-01')) AS BIGINT) AS start, event_type, count(*) AS cnt FROM events GROUP BY ALL")
def tumbling_counts(spark, sf_dir):
    return _plain(windows.window_counts(windows.events(spark, sf_dir), "1 day"), "start")


@query("SELECT CAST(epoch(time_bucket(INTERVAL 6 HOUR, CAST(ts AS TIMESTAMP), TIMESTAMP '1970-01-01')) AS BIGINT) - s * 21600 AS start, event_type, count(*) AS cnt FROM events, range(4) r(s) GROUP BY ALL")
def sliding_counts(spark, sf_dir):
    return _plain(windows.window_counts(windows.events(spark, sf_dir), "1 day", "6 hours"), "start")


@query("""WITH g AS (SELECT user_id, CAST(ts AS TIMESTAMP) AS ts, coalesce(ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) >= INTERVAL 6 HOUR, true) AS fresh FROM events),
    s AS (SELECT *, sum(CAST(fresh AS INTEGER)) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM g)
    SELECT user_id, CAST(floor(epoch(min(ts))) AS BIGINT) AS start, CAST(floor(epoch(max(ts) + INTERVAL 6 HOUR)) AS BIGINT) AS "end", count(*) AS cnt FROM s GROUP BY user_id, s""")
def session_counts(spark, sf_dir):
    return _plain(windows.session_counts(windows.events(spark, sf_dir), "6 hours"), "start", "end")


@query(f"""WITH b AS (SELECT DISTINCT user_id, CAST(epoch(time_bucket(INTERVAL 5 DAY, CAST(ts AS TIMESTAMP), TIMESTAMP '1970-01-01')) AS BIGINT) AS start, unnest(['type=' || event_type, 'band=' || {_BAND}]) AS i FROM events),
    n AS (SELECT start, count(DISTINCT user_id) AS n FROM b GROUP BY start), s AS (SELECT start, i, count(*) AS c FROM b GROUP BY ALL),
    p AS (SELECT a.start, a.i AS x, b.i AS y, count(*) AS cnt_xy FROM b a JOIN b USING (user_id, start) WHERE a.i <> b.i GROUP BY ALL)
    SELECT p.start, x AS antecedent, y AS consequent, cnt_xy, c AS cnt_x, n FROM p JOIN s ON s.start = p.start AND s.i = x JOIN n ON n.start = p.start WHERE cnt_xy * 100 >= 20 * n AND cnt_xy * 100 >= 60 * c""")
def windowed_rules(spark, sf_dir):
    return _plain(windows.mine_windowed(windows.events(spark, sf_dir), "5 days", "0.2", "0.6"), "start")


@query("""WITH s AS (SELECT event_type AS first, lead(event_type) OVER u AS second, epoch(CAST(lead(ts) OVER u AS TIMESTAMP)) - epoch(CAST(ts AS TIMESTAMP)) AS gap FROM events WINDOW u AS (PARTITION BY user_id ORDER BY ts, event_id))
    SELECT first, second, count(*) AS cnt FROM s WHERE gap <= 7200 GROUP BY ALL""")
def sequence_pairs(spark, sf_dir):
    return windows.sequence_pairs(windows.events(spark, sf_dir), 7200)


@query(f"SELECT item, count(*) AS cnt FROM (SELECT unnest(['type=' || event_type, 'band=' || {_BAND}]) AS item FROM events) GROUP BY item")
def streaming_root_counts(spark, sf_dir):
    return windows.streamed_root_counts(windows.event_stream(spark, sf_dir))
