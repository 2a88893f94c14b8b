"""Registered queries and, where SQL can express them, the DuckDB text that gives the same rows."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encoders import string_id_sql
from ..functions.hashing import HashFamily
from ..operators import bins as B
from ..operators import candidates as C
from ..operators import cells, costs, streams
from ..operators import rebuild as RB
from ..operators import reserve as R
from ..operators import similarity as S
from ..operators.replay import fault_log, replay
from ..schemas import INFINITE
from ..sources import collections as col
from ..sources.store import written
from ..sources.tables import read
from ..streaming.live import window_signatures
from . import relational
from . import workloads as W

K, RESERVE = 4, 4
AFFINE = HashFamily.affine(8, seed=3)
FEW = HashFamily.affine(K, seed=3)
TABULATION = HashFamily.tabulation(4, seed=5)
POLYNOMIAL = HashFamily.polynomial(4, degree=4, seed=7)
DOCS = HashFamily.affine(32, seed=9)
SHAPE = B.BinShape(bins=64, levels=12, seed=77)
#: The netted step begins after the updates below this share of the stream.
HALF = 0.5

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _register_collections() -> None:
    names = {
        "members_customer_parts": "customer_parts", "members_supplier_parts": "supplier_parts", "members_part_suppliers": "part_suppliers", "members_user_keys": "user_keys",
        "members_events_live": "user_keys_live", "doc_shingle_sets": "doc_shingles", "doc_word_sets": "doc_words", "benchmark_shingle_sets": "benchmark_shingles",
        "page_link_sets": "page_links", "conversation_word_sets": "conversation_words", "vector_topdim_sets": "vector_topdims", "nation_customer_sets": "nation_customers",
        "region_nation_sets": "region_nations",
    }
    for name, collection in names.items():
        QUERIES[name] = col.COLLECTIONS[collection]
        ORACLES[name] = col.COLLECTIONS_SQL[collection]


_register_collections()
UPDATES = col.EVENT_UPDATES_SQL
SUPPLIERS, PARTS, USERS, LIVE = (col.COLLECTIONS_SQL[n] for n in ("supplier_parts", "part_suppliers", "user_keys", "user_keys_live"))
SHINGLES = col.COLLECTIONS_SQL["doc_shingles"]


def _long_sql(members: str, family: HashFamily, k: int | None = None) -> str:
    """(set_id, slot, pair) of every member and slot."""
    return " UNION ALL ".join(f"SELECT set_id, {i} AS slot, {family.pair_sql(i, 'element')} AS pair FROM ({members})" for i in range(k or family.k))


def _sig_sql(members: str, family: HashFamily) -> str:
    return f"SELECT set_id, slot, min(pair) AS pair FROM ({_long_sql(members, family)}) GROUP BY 1, 2"


def _array_sig_sql(members: str, family: HashFamily) -> str:
    least = ", ".join(f"min({family.pair_sql(i, 'element')})" for i in range(family.k))
    return f"SELECT set_id, [{least}] AS sig FROM ({members}) GROUP BY 1"


def _agree_sql(a: str, b: str, k: int) -> str:
    return "(" + " + ".join(f"({a}[{i}] = {b}[{i}])::INT" for i in range(1, k + 1)) + f") / {k}.0::DOUBLE"


# Streams


@query(f"""SELECT seq, set_id, element, op, op <> coalesce(lag(op) OVER (PARTITION BY set_id, element ORDER BY seq, op), -1) AS legal FROM ({UPDATES})""")
def stream_flag_legal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.flag_legal(col.event_updates(spark, sf_dir)).select("seq", "set_id", "element", "op", "legal")


@query(f"SELECT max(seq) AS seq, set_id, element, arg_max(op, seq) AS op FROM ({UPDATES}) GROUP BY set_id, element")
def stream_net(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.net(col.event_updates(spark, sf_dir))


@query(f"""SELECT set_id, seq, (sum(op) OVER (PARTITION BY set_id ORDER BY seq, element, op ROWS UNBOUNDED PRECEDING))::BIGINT AS size
FROM (SELECT *, op <> coalesce(lag(op) OVER (PARTITION BY set_id, element ORDER BY seq, op), -1) AS legal FROM ({UPDATES})) WHERE legal""")
def stream_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.sizes(col.event_updates(spark, sf_dir))


EDGES = "SELECT DISTINCT o_custkey AS u, l_partkey + 1000000000 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' AND l_quantity >= 46"


@query(f"""WITH e AS ({EDGES}) SELECT DISTINCT x.u AS set_id, y.u AS element FROM e x JOIN e y ON x.v = y.v WHERE x.u <> y.u""")
def edge_two_hop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.neighbourhoods(col.thin_edges(spark, sf_dir), 2)


@query(f"""WITH e AS (SELECT row_number() OVER (ORDER BY u, v) AS seq, u, v FROM ({EDGES}))
SELECT seq, u AS set_id, v AS element, 1 AS op FROM e UNION ALL SELECT seq, v, u, 1 FROM e""")
def edge_set_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.edge_updates(W.numbered_edges(spark, sf_dir))


WHOLE_EDGES = "SELECT DISTINCT o_custkey AS u, l_partkey + 1000000000 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey"


@query()
def whole_edge_two_hop(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.neighbourhoods(col.edges(spark, sf_dir), 2)


@query(f"""WITH e AS (SELECT row_number() OVER (ORDER BY u, v) AS seq, u, v FROM ({WHOLE_EDGES}))
SELECT seq, u AS set_id, v AS element, 1 AS op FROM e UNION ALL SELECT seq, v, u, 1 FROM e""")
def whole_edge_set_updates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return streams.edge_updates(W.numbered_whole(spark, sf_dir))


# Signatures and similarity


@query(f"SELECT set_id, pair FROM ({_sig_sql(SUPPLIERS, AFFINE)}) WHERE slot = 0")
def minhash_supplier_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.minhash(col.supplier_parts(spark, sf_dir), AFFINE)


@query(_sig_sql(SUPPLIERS, AFFINE))
def signature_supplier_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.signatures(col.supplier_parts(spark, sf_dir), AFFINE, "long")


WIDE = HashFamily.affine(72, seed=21)


@query(_sig_sql(SUPPLIERS, WIDE))
def signature_kernel_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.signatures(col.supplier_parts(spark, sf_dir), WIDE, "long")


@query(_sig_sql(LIVE, TABULATION))
def signature_tabulation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.signatures(col.user_keys_live(spark, sf_dir), TABULATION, "long")


@query(_sig_sql(LIVE, POLYNOMIAL))
def signature_polynomial(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.signatures(col.user_keys_live(spark, sf_dir), POLYNOMIAL, "long")


def signature_native(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.signatures(col.supplier_parts(spark, sf_dir), HashFamily.native(8, 3), "long")


query()(signature_native)


@query(f"""SELECT set_id, r AS rank, pair FROM (SELECT set_id, pair, row_number() OVER (PARTITION BY set_id ORDER BY pair)::INT AS r
FROM ({_long_sql(SHINGLES, AFFINE, 1)})) WHERE r <= 16""")
def bottom_sketch_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return S.bottom_sketch(col.doc_shingles(spark, sf_dir), 16, AFFINE)


_PAIRS_OF = "SELECT a.set_id AS a, b.set_id AS b, a.{c} AS x, b.{c} AS y FROM s a JOIN s b ON a.set_id < b.set_id"


@query(f"""WITH s AS ({_array_sig_sql(USERS, AFFINE)}) SELECT a, b, {_agree_sql("x", "y", AFFINE.k)} AS est FROM ({_PAIRS_OF.format(c="sig")})""")
def estimate_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cells.estimates(S.signatures(col.user_keys(spark, sf_dir), AFFINE))


def _exact_sql(members: str, lam: float) -> str:
    return f"""WITH m AS ({members}), n AS (SELECT set_id, count(*) AS n FROM m GROUP BY 1),
t AS (SELECT a.set_id AS a, b.set_id AS b, count(*) AS c FROM m a JOIN m b ON a.element = b.element AND a.set_id < b.set_id GROUP BY 1, 2)
SELECT a, b, c / (x.n + y.n - c)::DOUBLE AS exact FROM t JOIN n x ON a = x.set_id JOIN n y ON b = y.set_id WHERE c / (x.n + y.n - c)::DOUBLE >= {lam}"""


@query(_exact_sql(PARTS, 0.35))
def exact_pairs_part_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.exact_pairs_in_cells(col.part_suppliers(spark, sf_dir), 0.35)


@query(_exact_sql(SHINGLES, 0.5))
def exact_pairs_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.exact_pairs_of_copies(col.doc_shingles(spark, sf_dir), 0.5)


@query(f"""WITH s AS ({_array_sig_sql(USERS, AFFINE)}), e AS (SELECT a, b, {_agree_sql("x", "y", AFFINE.k)} AS est FROM ({_PAIRS_OF.format(c="sig")})),
j AS (SELECT est, exact, floor(exact * 10)::INT AS tenth FROM e JOIN ({_exact_sql(USERS, 0.0)}) USING (a, b))
SELECT tenth, round(sqrt(avg((est - exact) * (est - exact))), 9) AS rmse, round(stddev_samp(est - exact), 9) AS error_sd, count(*) AS pairs FROM j GROUP BY 1""")
def rmse_by_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = cells.signature_errors(col.user_keys(spark, sf_dir), [AFFINE], by_tenth=True, sharing=True)
    return found.select("tenth", F.round("rmse", 9).alias("rmse"), F.round("error_sd", 9).alias("error_sd"), "pairs")


# The reserve sketch

_RANKED = """SELECT set_id, slot, pair FROM (SELECT *, row_number() OVER (PARTITION BY set_id, slot ORDER BY pair) AS r FROM ({long})) WHERE r <= {l}"""


@query(_RANKED.format(long=_long_sql(SUPPLIERS, FEW), l=RESERVE))
def reserve_init_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.reserve_long(col.supplier_parts(spark, sf_dir), FEW, RESERVE)


@query(f"""SELECT set_id, slot, count(*) AS size, CASE WHEN count(*) >= {RESERVE} THEN max(pair) ELSE {INFINITE} END AS lim
FROM ({_RANKED.format(long=_long_sql(LIVE, FEW), l=RESERVE)}) GROUP BY 1, 2""")
def reserve_limits_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.limits_of(R.reserve_long(col.user_keys_live(spark, sf_dir), FEW, RESERVE), RESERVE)


def _signature_rows(sigs: DataFrame) -> DataFrame:
    return sigs.where("sig is not null").select("set_id", F.posexplode("sig").alias("slot", "pair"))


@query(_sig_sql(LIVE, FEW))
def reserve_signature_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _signature_rows(R.reserve_signature(R.reserve_init(col.user_keys_live(spark, sf_dir), FEW, RESERVE)))


@query(_sig_sql(SUPPLIERS, FEW))
def reserve_sampled_init(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _signature_rows(R.reserve_signature(R.reserve_init(col.supplier_parts(spark, sf_dir), FEW, RESERVE, sampled=True)))


def _netted(spark: SparkSession, sf_dir: str, reserve: int = RESERVE) -> tuple[DataFrame, DataFrame, DataFrame]:
    updates = col.event_updates(spark, sf_dir)
    split = F.broadcast(updates.agg((F.max("seq") * HALF).alias("split")))  # one row
    marked = updates.join(split)
    first, second = marked.where("seq < split").drop("split"), marked.where("seq >= split").drop("split")
    members = streams.members_at(updates)
    before = R.reserve_init(streams.members_at(first), FEW, reserve)
    return *R.reserve_apply(before, second, members, FEW, reserve), members


def _netted_sql(reserve: int) -> str:
    return f"""u AS ({UPDATES}), h AS (SELECT max(seq) * {HALF} AS split FROM u),
m0 AS (SELECT set_id, element FROM (SELECT set_id, element, arg_max(op, seq) AS op FROM u, h WHERE seq < split GROUP BY 1, 2) WHERE op = 1),
m1 AS (SELECT set_id, element FROM (SELECT set_id, element, arg_max(op, seq) AS op FROM u GROUP BY 1, 2) WHERE op = 1),
o AS (SELECT set_id, element, arg_max(op, seq) AS op FROM u, h WHERE seq >= split GROUP BY 1, 2),
i0 AS ({_RANKED.format(long=_long_sql("SELECT * FROM m0", FEW), l=reserve)}),
l0 AS (SELECT set_id, slot, CASE WHEN count(*) >= {reserve} THEN max(pair) ELSE {INFINITE} END AS lim FROM i0 GROUP BY 1, 2),
put AS ({_long_sql("SELECT * FROM o WHERE op = 1", FEW)}), gone AS ({_long_sql("SELECT * FROM o WHERE op = -1", FEW)}),
both_ AS (SELECT * FROM (SELECT * FROM i0 EXCEPT SELECT * FROM gone) UNION SELECT p.* FROM put p LEFT JOIN l0 USING (set_id, slot) WHERE p.pair <= coalesce(lim, {INFINITE})),
i1 AS ({_RANKED.format(long="SELECT * FROM both_", l=reserve)}),
c1 AS (SELECT set_id, slot, count(*) AS size, max(pair) AS top, min(pair) AS pair FROM i1 GROUP BY 1, 2),
bare AS (SELECT l0.set_id, min(slot) AS slot FROM l0 ANTI JOIN c1 USING (set_id, slot) WHERE lim < {INFINITE} AND set_id IN (SELECT set_id FROM o) GROUP BY 1),
again AS ({_RANKED.format(long=_long_sql("SELECT m1.* FROM m1 JOIN bare USING (set_id)", FEW), l=reserve)})"""


_NETTED = _netted_sql(RESERVE)
#: A reserve so small that batches do fault.
SMALL_RESERVE = 1


@query(f"""WITH {_NETTED}
SELECT set_id, slot, size, pair, CASE WHEN size >= {RESERVE} THEN top ELSE coalesce(lim, {INFINITE}) END AS lim FROM c1 LEFT JOIN l0 USING (set_id, slot) WHERE set_id NOT IN (SELECT set_id FROM bare)
UNION ALL SELECT set_id, slot, count(*), min(pair), CASE WHEN count(*) >= {RESERVE} THEN max(pair) ELSE {INFINITE} END FROM again GROUP BY 1, 2""")
def reserve_netted_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    sketch, _, _ = _netted(spark, sf_dir)
    slots = sketch.select("set_id", F.posexplode("slots").alias("slot", "s")).where(F.size("s.pairs") > 0)
    return slots.select("set_id", "slot", F.size("s.pairs").cast("bigint").alias("size"), F.element_at("s.pairs", 1).alias("pair"), F.col("s.lim").alias("lim"))


@query(f"WITH {_netted_sql(SMALL_RESERVE)} SELECT set_id, slot::INT AS slot, (SELECT count(*) FROM m1 WHERE m1.set_id = bare.set_id) AS size_after FROM bare")
def reserve_netted_faults(spark: SparkSession, sf_dir: str) -> DataFrame:
    _, faults, _ = _netted(spark, sf_dir, SMALL_RESERVE)
    return faults.select("set_id", "slot", "size_after")


@query("SELECT 0::BIGINT AS violations")
def reserve_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    sketch, _, members = _netted(spark, sf_dir)
    return R.audit(sketch, members, FEW, RESERVE).agg(F.coalesce(F.sum("bad"), F.lit(0)).cast("bigint").alias("violations"))


@query(_sig_sql(SUPPLIERS, FEW))
def reserve_merge_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    members = col.supplier_parts(spark, sf_dir)
    shards = [R.reserve_init(members.where(F.col("element") % 3 == i), FEW, RESERVE) for i in range(3)]
    return _signature_rows(R.reserve_signature(R.reserve_agg(reduce(DataFrame.unionByName, shards), RESERVE)))


@query(f"""SELECT set_id, CASE WHEN count(*) < {RESERVE} THEN {K} * (count(*) + 1) ELSE {K} * {RESERVE + 1} END AS words FROM ({LIVE}) GROUP BY 1""")
def reserve_memory_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return R.memory_words(R.reserve_init(col.user_keys_live(spark, sf_dir), FEW, RESERVE))


@query(f"SELECT set_id, len(e) AS n FROM (SELECT set_id, list(element) AS e FROM ({EDGES.replace('AS u', 'AS set_id').replace('AS v', 'AS element')}) GROUP BY 1) WHERE len(e) < {RESERVE}")
def reserve_compact(spark: SparkSession, sf_dir: str) -> DataFrame:
    members = streams.neighbourhoods(col.thin_edges(spark, sf_dir), 1)
    small = R.compact(R.reserve_init(members, FEW, RESERVE)).where("elements is not null")
    return small.select("set_id", F.size("elements").cast("bigint").alias("n"))


@query(f"SELECT set_id, len(e) AS n FROM (SELECT set_id, list(element) AS e FROM ({WHOLE_EDGES.replace('AS u', 'AS set_id').replace('AS v', 'AS element')}) GROUP BY 1) WHERE len(e) < {RESERVE}")
def whole_reserve_compact(spark: SparkSession, sf_dir: str) -> DataFrame:
    small = R.compact(R.reserve_init(streams.neighbourhoods(col.edges(spark, sf_dir), 1), FEW, RESERVE)).where("elements is not null")
    return small.select("set_id", F.size("elements").cast("bigint").alias("n"))


# Sequential replay


def _replayed(kind: str, family: HashFamily = FEW, sql: str | None = _sig_sql(LIVE, FEW), legal: bool = False, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        updates = col.event_updates(spark, sf_dir)
        return _signature_rows(replay(streams.legalize(updates) if legal else updates, kind, family, RESERVE, **options))

    run.__name__ = f"{kind}_replay_signature"
    query(sql)(run)


_replayed("reserve")
_replayed("unordered")
_replayed("strict")
_replayed("rebuild")
_replayed("hash_only", legal=True, sql=" UNION ALL ".join(f"SELECT set_id, {i} AS slot, min({FEW.hash_sql(i, 'element')}) AS pair FROM ({LIVE}) GROUP BY 1" for i in range(K)))


def _faults(kind: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return costs.fault_counts(replay(col.event_updates(spark, sf_dir), kind, DOCS, 2, shape=SHAPE))

    run.__name__ = f"{kind}_replay_faults"
    query()(run)


for _kind in ("reserve", "rebuild", "strict", "eager_bins"):
    _faults(_kind)


@query()
def naive_replay_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many sets the naive buffer gets wrong."""
    updates = col.event_updates(spark, sf_dir)
    right = S.signatures(streams.members_at(updates), DOCS).withColumnRenamed("sig", "right")
    both = replay(updates, "naive", DOCS, 2).join(right, "set_id", "left")
    return both.agg(F.count(F.lit(1)).alias("sets"), F.count(F.when(~F.col("sig").eqNullSafe(F.col("right")), 1)).alias("wrong"))


@query()
def reserve_fault_log(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fault_log(replay(col.event_updates(spark, sf_dir), "reserve", DOCS, 1))


# Rebuild baseline


def _rebuilt(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    updates = col.event_updates(spark, sf_dir)
    marked = updates.join(F.broadcast(updates.agg((F.max("seq") * HALF).alias("split"))))
    before = RB.rebuild_init(streams.members_at(marked.where("seq < split")), FEW)
    return RB.rebuild_apply(before, marked.where("seq >= split").drop("split"), streams.members_at(updates), FEW)


@query(_sig_sql(LIVE, FEW))
def rebuild_apply_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _signature_rows(_rebuilt(spark, sf_dir)[0])


@query(f"WITH {_NETTED}, s0 AS (SELECT set_id, slot, min(pair) AS pair FROM i0 GROUP BY 1, 2) SELECT DISTINCT set_id FROM s0 JOIN gone USING (set_id, slot, pair)")
def rebuild_fault_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _rebuilt(spark, sf_dir)[1]


# Bin sketch

LEGAL = f"SELECT * FROM (SELECT *, op <> coalesce(lag(op) OVER (PARTITION BY set_id, element ORDER BY seq, op), -1) AS legal FROM ({UPDATES})) WHERE legal"
COUNTERS = f"""SELECT set_id, {SHAPE.level_sql("element")} AS level, {SHAPE.bin_sql("element")} AS bin, sum(op)::BIGINT AS cnt FROM ({LEGAL}) GROUP BY ALL HAVING sum(op) <> 0"""


def _counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return B.bins_apply(None, streams.legalize(col.event_updates(spark, sf_dir)), SHAPE)


@query(COUNTERS)
def bins_counters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _counters(spark, sf_dir)


@query(f"""SELECT count(*) AS drifted FROM (SELECT set_id, {SHAPE.level_sql("element")} AS level, {SHAPE.bin_sql("element")} AS bin, sum(op) AS c FROM ({UPDATES}) GROUP BY ALL)
FULL JOIN ({COUNTERS}) USING (set_id, level, bin) WHERE coalesce(c, 0) <> coalesce(cnt, 0)""")
def bins_nonlegal_drift(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counters that an arbitrary stream leaves different from the legal one's."""
    raw = B.bins_apply(None, col.event_updates(spark, sf_dir), SHAPE).withColumnRenamed("cnt", "c")
    zero = F.lit(0).cast("bigint")
    both = raw.join(_counters(spark, sf_dir), ["set_id", "level", "bin"], "full")
    return both.agg(F.count(F.when(F.coalesce("c", zero) != F.coalesce("cnt", zero), 1)).alias("drifted"))


LEVELS = f"SELECT set_id, {SHAPE.level_for_sql('sum(cnt)')} AS level FROM ({COUNTERS}) GROUP BY 1"
LEVEL_SETS = f"SELECT c.set_id, c.bin::BIGINT AS element FROM ({COUNTERS}) c JOIN ({LEVELS}) l ON c.set_id = l.set_id AND c.level = l.level"


@query(LEVEL_SETS)
def bins_level_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    counters = _counters(spark, sf_dir)
    levels = B.bins_sizes(counters).select("set_id", SHAPE.level_for(F.col("n")).alias("level"))
    return B.bins_level(counters, levels)


@query(_sig_sql(LEVEL_SETS, FEW))
def bins_signature(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _signature_rows(B.bins_signature(_counters(spark, sf_dir), FEW, SHAPE))


@query(f"""WITH c AS ({COUNTERS}), n AS (SELECT set_id, sum(cnt) AS n FROM c GROUP BY 1),
p AS (SELECT x.set_id AS a, y.set_id AS b, {SHAPE.level_for_sql("greatest(x.n, y.n)")} AS level FROM n x JOIN n y ON x.set_id < y.set_id),
m AS (SELECT set_id, level, count(*) AS m FROM c GROUP BY 1, 2),
t AS (SELECT a, b, count(*) AS c FROM p JOIN c x ON x.set_id = a AND x.level = p.level JOIN c y ON y.set_id = b AND y.level = p.level AND y.bin = x.bin GROUP BY 1, 2)
SELECT a, b, CASE WHEN coalesce(x.m, 0) + coalesce(y.m, 0) > 0 THEN coalesce(t.c, 0) / (coalesce(x.m, 0) + coalesce(y.m, 0) - coalesce(t.c, 0))::DOUBLE END AS est
FROM p LEFT JOIN m x ON x.set_id = a AND x.level = p.level LEFT JOIN m y ON y.set_id = b AND y.level = p.level LEFT JOIN t USING (a, b)""")
def bins_similarity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cells.bin_estimates(_counters(spark, sf_dir), SHAPE)


@query(" UNION ALL ".join(f"SELECT set_id, level, {i} AS slot, min({FEW.pair_sql(i, 'bin::BIGINT')}) AS pair FROM ({COUNTERS}) GROUP BY 1, 2" for i in range(K)))
def bins_eager_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Kept minima after a second half of the legal stream; equal to those read from the final counters."""
    updates = streams.legalize(col.event_updates(spark, sf_dir))
    marked = updates.join(F.broadcast(updates.agg((F.max("seq") * HALF).alias("split"))))
    first = B.bins_apply(None, marked.where("seq < split"), SHAPE)
    _, sigs = B.bins_eager_apply(first, B.bins_eager_init(first, FEW), marked.where("seq >= split").drop("split"), SHAPE, FEW)
    return sigs.select("set_id", "level", F.posexplode("sig").alias("slot", "pair"))


# Candidate pairs

BANDS, ROWS, LAM = 8, 4, 0.5
_KEYS = f"""SELECT set_id, band, array_to_string(sig[band * {ROWS} + 1:band * {ROWS} + {ROWS}], '-') AS key FROM ({_array_sig_sql(SHINGLES, DOCS)}), (SELECT unnest(range({BANDS})) AS band)"""
_CANDIDATES = f"SELECT DISTINCT x.set_id AS a, y.set_id AS b FROM k x JOIN k y ON x.band = y.band AND x.key = y.key AND x.set_id < y.set_id"


def _doc_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signatures that are read more than once: texts are shingled a single time."""
    return written(S.signatures(col.doc_shingles(spark, sf_dir), DOCS), "signatures")


@query(f"WITH k AS ({_KEYS}) {_CANDIDATES}")
def candidate_pairs_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.candidate_pairs(_doc_signatures(spark, sf_dir), BANDS, ROWS, text=True)


@query(f"WITH k AS ({_KEYS}) {_CANDIDATES}")
def candidate_pairs_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.candidate_pairs(_doc_signatures(spark, sf_dir), BANDS, ROWS, max_bucket=3, hot="salt")


@query(f"WITH k AS ({_KEYS}) {_CANDIDATES}")
def candidate_pairs_collapsed(spark: SparkSession, sf_dir: str) -> DataFrame:
    sigs = _doc_signatures(spark, sf_dir)
    kept, membership = C.collapse_identical(sigs)
    return C.expand_pairs(C.candidate_pairs(kept, BANDS, ROWS), membership)


_QUALITY = f"""WITH k AS ({_KEYS}), r AS ({_CANDIDATES}), t AS (SELECT a, b FROM ({_exact_sql(SHINGLES, LAM)})), m AS (SELECT count(DISTINCT set_id) AS m FROM k),
c AS (SELECT count(*) FILTER (r.a IS NOT NULL AND t.a IS NOT NULL) AS tp, count(*) FILTER (t.a IS NULL) AS fp, count(*) FILTER (r.a IS NULL) AS fn FROM r FULL JOIN t ON r.a = t.a AND r.b = t.b)
SELECT tp, fp, fn, (m * (m - 1) // 2 - tp - fp - fn)::BIGINT AS tn, round(tp / nullif(tp + fp, 0)::DOUBLE, 9) AS precision, round(tp / nullif(tp + fn, 0)::DOUBLE, 9) AS recall,
round(2 * tp / nullif(2 * tp + fp + fn, 0)::DOUBLE, 9) AS f1, tp + fn AS effective, tp + fp AS returned FROM c, m"""


@query(_QUALITY)
def candidate_quality_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    copies = C.Copies(col.doc_shingles(spark, sf_dir))
    sigs = written(S.signatures(copies.leaders, DOCS), "signatures")
    return C.quality_of_copies(copies, C.candidate_pairs(sigs, BANDS, ROWS), LAM)


@query(f"""WITH s AS ({_array_sig_sql(SHINGLES, DOCS)}), k AS ({_KEYS}), c AS ({_CANDIDATES})
SELECT a, b, {_agree_sql("x.sig", "y.sig", DOCS.k)} AS est FROM c JOIN s x ON a = x.set_id JOIN s y ON b = y.set_id WHERE {_agree_sql("x.sig", "y.sig", DOCS.k)} >= {LAM}""")
def verify_pairs_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    sigs = _doc_signatures(spark, sf_dir)
    return C.verify_pairs(C.candidate_pairs(sigs, BANDS, ROWS), sigs, LAM)


@query(f"WITH k AS ({_KEYS}), c AS ({_CANDIDATES}) SELECT e.* FROM ({_exact_sql(SHINGLES, LAM)}) e SEMI JOIN c ON e.a = c.a AND e.b = c.b")
def verify_exact_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    copies = C.Copies(col.doc_shingles(spark, sf_dir))
    found = C.candidate_pairs(written(S.signatures(copies.leaders, DOCS), "signatures"), BANDS, ROWS)
    return copies.expand(copies.exact(found).where(F.col("exact") >= LAM))


_BENCH = col.COLLECTIONS_SQL["benchmark_shingles"]


@query(f"""WITH d AS ({_array_sig_sql(SHINGLES, DOCS)}), q AS (SELECT -1 - set_id AS set_id, sig FROM ({_array_sig_sql(_BENCH, DOCS)})),
g AS (SELECT unnest(range({DOCS.k})) AS band)
SELECT DISTINCT q.set_id AS query_id, d.set_id, {_agree_sql("q.sig", "d.sig", DOCS.k)} AS est FROM d, q, g
WHERE d.sig[band + 1] = q.sig[band + 1]""")
def search_benchmark_docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that meet a benchmark item in one value of their signatures; items have negative ids."""
    items = S.signatures(col.benchmark_shingles(spark, sf_dir), DOCS).select((F.lit(-1).cast("bigint") - F.col("set_id")).alias("set_id"), "sig")
    return C.similar_to(_doc_signatures(spark, sf_dir), items, DOCS.k, 1, 0.0)


@query(f"""WITH s AS ({_array_sig_sql(USERS, AFFINE)}), e AS (SELECT a, b, {_agree_sql("x", "y", AFFINE.k)} AS est FROM ({_PAIRS_OF.format(c="sig")})),
f AS (SELECT a AS set_id, b AS other, est FROM e UNION ALL SELECT b, a, est FROM e)
SELECT set_id, rank, other, est FROM (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY est DESC, other)::INT AS rank FROM f) WHERE rank <= 3""")
def top_similar_users(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.top_similar_of_all(S.signatures(col.user_keys(spark, sf_dir), AFFINE), 3)


GRID = [0.25, 0.3, 0.35, 0.4, 0.45]


@query(f"""WITH e AS ({_exact_sql(USERS, min(GRID))}), m AS (SELECT count(DISTINCT set_id) AS m FROM ({USERS}))
SELECT lam, count(*) FILTER (exact >= lam) AS pairs, count(*) FILTER (exact >= lam) / (any_value(m) * (any_value(m) - 1) / 2.0)::DOUBLE AS share,
count(*) FILTER (exact >= lam) / (any_value(m) * (any_value(m) - 1) / 2.0)::DOUBLE <= 0.04 AS fits FROM e, m, (SELECT unnest({GRID}::DOUBLE[]) AS lam) GROUP BY 1""")
def threshold_choice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return C.choose_threshold(col.user_keys(spark, sf_dir), GRID, dense=True)


# Formulas

#: Sizes of all suppliers' sets, how many of their parts came back, and the similarity of each with the set of all parts.
SIZES = """SELECT l_suppkey AS set_id, count(*) AS n, sum(came_back)::BIGINT AS deleted FROM (SELECT l_suppkey, l_partkey, max((l_returnflag = 'R')::INT) AS came_back
FROM lineitem WHERE l_suppkey IS NOT NULL AND l_partkey IS NOT NULL GROUP BY 1, 2) GROUP BY 1"""
SHARES = f"SELECT set_id, n / (SELECT count(DISTINCT l_partkey) FROM lineitem)::DOUBLE AS s FROM ({SIZES})"


def _sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return W.returned_parts(spark, sf_dir).groupBy("set_id").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("came_back").cast("bigint")).alias("deleted"))


def _shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    every = read(spark, sf_dir, "lineitem").agg(F.countDistinct("l_partkey").alias("every"))  # one row
    return _sizes(spark, sf_dir).join(F.broadcast(every)).select("set_id", (F.col("n") / F.col("every")).alias("s"))


def _values(rows) -> str:
    return ", ".join("(" + ", ".join(repr(x) + ("::DOUBLE" if isinstance(x, float) else "") for x in r) + ")" for r in rows)


def _each(rows: list[tuple], names: list[str]) -> Column:
    """One row for each of a few settings."""
    return F.inline(F.array(*[F.struct(*[F.lit(x).alias(c) for x, c in zip(r, names)]) for r in rows]))


CURVE = [(700, 3), (400, 2), (150, 5), (150, 6)]


@query(f"""SELECT set_id, bands, n_rows, s, round(1 - pow(1 - pow(s, n_rows), bands), 9) AS p FROM ({SHARES}), (VALUES {_values(CURVE)}) t(bands, n_rows)""")
def band_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chance that each supplier's set and the set of all parts become candidates."""
    rows = _shares(spark, sf_dir).select("set_id", "s", _each(CURVE, ["bands", "n_rows"]))
    return rows.select("set_id", "bands", "n_rows", "s", F.round(C.band_probability_column(F.col("s"), F.col("bands"), F.col("n_rows")), 9).alias("p"))


#: gamma, delta and gamma^4 delta^5.
GUARANTEES = [(g, d, g**4 * d**5) for g, d in ((0.2, 0.1), (0.1, 0.1), (0.3, 0.2), (0.2, 5.62))]


@query(f"""SELECT set_id, r1, r2, gamma, delta, round((1 - gamma) * r1, 9) AS p1, round(6 * r2 / (delta * (1 - gamma * sqrt(2 * r1) / 5)), 9) AS p2, round(1 - delta, 9) AS probability,
round(1 / (spread * (r1 * r1)), 3) AS c2 FROM (SELECT set_id, s AS r1, s / 2 AS r2 FROM ({SHARES})), (VALUES {_values(GUARANTEES)}) t(gamma, delta, spread)""")
def bins_guarantee_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Guarantees of the bin sketch at the similarity of each supplier's set and the set of all parts, against half of it."""
    rows = _shares(spark, sf_dir).select("set_id", F.col("s").alias("r1"), (F.col("s") / 2).alias("r2"), _each(GUARANTEES, ["gamma", "delta", "spread"]))
    r1, r2, gamma, delta = (F.col(c) for c in ("r1", "r2", "gamma", "delta"))
    p2 = 6 * r2 / (delta * (1 - gamma * F.sqrt(2 * r1) / 5))
    c2 = F.round(1 / (F.col("spread") * (r1 * r1)) * 1000) / 1000  # as the SQL rounds; Spark's round(x, 3) differs where x is large
    return rows.select("set_id", "r1", "r2", "gamma", "delta", F.round((1 - gamma) * r1, 9).alias("p1"), F.round(p2, 9).alias("p2"), F.round(1 - delta, 9).alias("probability"), c2.alias("c2"))


FAULT_RESERVES = [(ell,) for ell in (1, 2, 4, 8, 16, 32)]


@query(f"""SELECT set_id, deleted, n, reserve, CASE WHEN deleted < reserve THEN 0 ELSE round(pow(deleted / n::DOUBLE, reserve), 9) END AS bound FROM ({SIZES}), (VALUES {_values(FAULT_RESERVES).replace(",)", ")")}) t(reserve)""")
def fault_bound_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bound on the chance that a slot loses its whole reserve when a supplier's returned parts are deleted."""
    rows = _sizes(spark, sf_dir).select("set_id", "deleted", "n", _each(FAULT_RESERVES, ["reserve"]))
    bound = F.when(F.col("deleted") < F.col("reserve"), 0.0).otherwise(F.round(F.pow(F.col("deleted") / F.col("n"), F.col("reserve")), 9))
    return rows.withColumn("bound", bound)


@query(f"""SELECT set_id, t.* REPLACE (CASE WHEN sketch = 'rebuild' THEN 2000 * n ELSE update_cost END::DOUBLE AS update_cost) FROM ({SIZES}),
(VALUES ('rebuild', 2000.0::DOUBLE, 0.0::DOUBLE, false, 2000.0::DOUBLE, 0.7::DOUBLE, 0.5::DOUBLE, 1.0::DOUBLE),
('bins', 32768.0::DOUBLE, 1.0::DOUBLE, false, 2048000.0::DOUBLE, round((1 - 0.2::DOUBLE) * 0.7::DOUBLE, 9), round(6 * 0.5::DOUBLE / (0.1::DOUBLE * (1 - 0.2::DOUBLE * sqrt(1.4::DOUBLE) / 5)), 9), 0.9::DOUBLE),
('reserve', 64000.0::DOUBLE, 64000.0::DOUBLE, true, 2000.0::DOUBLE, 0.7::DOUBLE, 0.5::DOUBLE, 1.0::DOUBLE)) t(sketch, space, update_cost, amortized, query_cost, p1, p2, probability)""")
def cost_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds of the three sketches for each supplier's set."""
    rows = costs.cost_rows(_sizes(spark, sf_dir), k=2000, universe_bits=32, bins=1024, r1=0.7, r2=0.5, gamma=0.2, delta=0.1)
    return rows.withColumns({c: F.round(c, 9) for c in ("p1", "p2", "probability")})


# Relational surface around the sketches


@query(f"""SELECT event_type, day, count(*) AS updates, count(DISTINCT user_id) AS users FROM (SELECT event_type, user_id, date_trunc('day', ts)::DATE AS day FROM events) GROUP BY CUBE (event_type, day)""")
def update_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_type", "user_id", F.to_date("ts").alias("day"))
    return rows.cube("event_type", "day").agg(F.count(F.lit(1)).alias("updates"), F.countDistinct("user_id").alias("users"))


@query(f"""WITH p AS (SELECT set_id, element, date_trunc('day', ts) AS window_start FROM ({UPDATES}) WHERE op = 1)
{" UNION ALL ".join(f"SELECT window_start, set_id, {i} AS slot, min({FEW.pair_sql(i, 'element')}) AS pair FROM p GROUP BY 1, 2" for i in range(K))}""")
def window_signatures_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    sigs = window_signatures(col.event_updates(spark, sf_dir), FEW, "1 day")
    return sigs.select("window_start", "set_id", F.posexplode("sig").alias("slot", "pair"))


@query(f"""WITH s AS ({_array_sig_sql(SHINGLES, DOCS)}), k AS ({_KEYS}), c AS ({_CANDIDATES}),
e AS (SELECT a, b, {_agree_sql("x.sig", "y.sig", DOCS.k)} AS est FROM c JOIN s x ON a = x.set_id JOIN s y ON b = y.set_id)
SELECT quality, toxic, count(*) AS pairs, round(avg(est), 9) AS mean_est FROM e JOIN labels ON a = doc_id GROUP BY 1, 2""")
def pairs_by_label(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidate pairs sliced by the labels of their first document."""
    sigs = _doc_signatures(spark, sf_dir)
    est = S.estimate_similarity(sigs, C.candidate_pairs(sigs, BANDS, ROWS))
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return est.join(labels, F.col("a") == F.col("doc_id")).groupBy("quality", "toxic").agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg("est"), 9).alias("mean_est"))


W.register(query)
relational.register(query)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, est): reserve sketches kept over the whole update stream, then the pairs their signatures make candidates."""
    family, reserve = HashFamily.affine(72, seed=3), R.choose_reserve(8)
    updates = col.event_updates(spark, sf_dir)
    marked = updates.join(F.broadcast(updates.agg((F.max("seq") * HALF).alias("split"))))  # one row
    before = R.reserve_init(streams.members_at(marked.where("seq < split")), family, reserve)
    sketch, _ = R.reserve_apply(before, marked.where("seq >= split").drop("split"), streams.members_at(updates), family, reserve)
    return cells.estimates(R.reserve_signature(sketch), 0.3, bands=36, rows=2)


query()(flagship)
