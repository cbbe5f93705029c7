"""The registered method queries and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import measures, oracles
from .operators import baselines, bottom_up, linear
from .operators.binarize import binary_extension, cap_degree, default_cap, degrees, start
from .operators.finite import Prepared, prepare_tree, solve, values_per_vertex
from .operators.problems import PROBLEMS, colouring, edge_cover, independent_dominating_set, r_hop_domination
from .operators.recover import recover
from .operators.relational import OPS
from .plans import schedule
from .plans.decompose import Rules, decompose
from .plans.hashing import PolyHash, distribute
from .plans.iterate import materialise, scratch_folder
from .sources import trees
from .streaming.online import batch_chain, dedup_events, events_stream, join_static, purchases_after_views, run_available

Query = Callable[[SparkSession, str], DataFrame]

KINDS = ("chain_user", "chain_all", "heap", "random", "catalog", "customers", "star", "threads", "corpus")
SMALL_STATE = ("mwm", "mcm", "mvc", "mis", "mds", "lpath")
FOLDS = ("height", "subtree_sum", "subtree_size")
MACHINES = 8
#: Pieces for tables that grow with the subtree on whole tables: a piece's own table is quadratic in it.
WHOLE_MACHINES = 32

_ready: dict[tuple[str, str, str, str], Prepared] = {}


def clear_cache() -> None:
    """Forgets prepared trees, so that a timed query pays for its whole work."""
    _ready.clear()


def _state(spark: SparkSession, sf_dir: str, table: str | None) -> str:
    """Names, lengths and times of the input's files, so that a changed table is not answered from an older tree."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/{table}.parquet" if table else sf_dir)
    files = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return " ".join(f"{f.getPath()}:{f.getLen()}:{f.getModificationTime()}" for f in files.listStatus(path))


def ready(spark: SparkSession, sf_dir: str, kind: str) -> Prepared:
    """A workload tree, made binary and decomposed once for each session and state of the input; all problems share it."""
    table = "events" if kind in ("chain_user", "chain_all", "heap", "random", "caterpillar") else None
    key = (spark.sparkContext.applicationId, sf_dir, kind, _state(spark, sf_dir, table))
    if key not in _ready:
        _ready[key] = prepare_tree(materialise(trees.tree(spark, sf_dir, kind), "tree"), MACHINES)
    return _ready[key]


def _answer(kind: str, problem: str) -> Query:
    def run(spark, sf_dir):
        return solve(ready(spark, sf_dir, kind), PROBLEMS[problem]()).select("tree_id", "problem", "value")

    return run


def ready_tree(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """The original vertices of a prepared tree."""
    bt = ready(spark, sf_dir, kind).bt
    return measures.original_parents(bt).join(bt.where("NOT is_aux").select("tree_id", F.shiftright("node_id", 2).alias("node_id"), "node_w", "edge_w"), ["tree_id", "node_id"])


def _pieces_of(spark: SparkSession, sf_dir: str, size: int) -> int:
    """As many machines as make shares of about `size` events."""
    return max(1, trees.load(spark, sf_dir, "events").count() // size)


def _merge_work(p: Prepared) -> DataFrame:
    return measures.merge_work(p, schedule.build(p.dec.comp), max(256, -(-p.dec.n // max(1, int(p.dec.m**0.5)))))


def _value(df: DataFrame) -> DataFrame:
    return df.select("tree_id", "value")


def _checks(spark: SparkSession, checks: dict[str, bool]) -> DataFrame:
    return spark.createDataFrame([tuple(checks.values())], ", ".join(f"{k} boolean" for k in checks))


def _broken(bt: DataFrame) -> bool:
    dec = decompose(bt, 64, rules=Rules(below_completed=False, stop_factor=1, max_iterations=30), local_rows=1 << 40)
    return measures.check_connected(bt, dec.assign) > 0


def _dec_valid(kind: str, **options) -> Query:
    def run(spark, sf_dir):
        p = ready(spark, sf_dir, kind) if not options else prepare_tree(trees.tree(spark, sf_dir, kind), MACHINES, **options)
        return _checks(spark, measures.check_decomposition(p.bt, p.dec))

    return run


_DEC_SQL = "SELECT true AS covers, true AS connected, true AS few_pieces, true AS \"binary\", true AS bounded_pieces"
_HALF = "(SELECT count(*) FROM tree) // 2"


def _method_queries() -> dict[str, tuple[Query, str | None]]:
    q: dict[str, tuple[Query, str | None]] = {}
    for kind in KINDS:
        for problem in (*SMALL_STATE, *FOLDS):
            q[f"{problem}_{kind}"] = (_answer(kind, problem), oracles.answers(kind, problem))
    for kind in ("caterpillar", "broom"):
        for problem in SMALL_STATE:
            q[f"{problem}_{kind}"] = (_answer(kind, problem), oracles.answers(kind, problem))
    for kind in ("site", "mst"):
        for problem in ("mis", "mwm", "mds"):
            q[f"{problem}_{kind}"] = (_answer(kind, problem), None)
    # ---- the distributed loop to its end, without a local finish ----
    for kind, problem in (("chain_all", "mis"), ("random", "mwm"), ("heap", "mds"), ("catalog", "mwm"), ("broom", "mwm")):
        q[f"{problem}_distributed_{kind}"] = (
            lambda spark, d, kind=kind, problem=problem: solve(prepare_tree(trees.tree(spark, d, kind), MACHINES, local_rows=0), PROBLEMS[problem]()).select("tree_id", "problem", "value"),
            oracles.answers(kind, problem),
        )
    # ---- other numbers of machines ----
    for m in (2, 4, 32):
        q[f"mwm_random_m{m}"] = (lambda spark, d, m=m: solve(trees.random(spark, d), PROBLEMS["mwm"](), m).select("tree_id", "problem", "value"), oracles.answers("random", "mwm"))
    # ---- degrees and binary extension ----
    for kind in ("catalog", "heap", "star"):
        q[f"deg_{kind}"] = (
            lambda spark, d, kind=kind: degrees(trees.tree(spark, d, kind)).select("node_id", "degree"),
            f"WITH {oracles.levels(kind).split(', lev AS')[0]} SELECT t.node_id, count(c.node_id) AS degree FROM tree t LEFT JOIN tree c ON c.parent_id = t.node_id GROUP BY t.node_id",
        )
        q[f"bin_parent_roundtrip_{kind}"] = (
            lambda spark, d, kind=kind: measures.original_parents(ready(spark, d, kind).bt).select("node_id", "parent_id"),
            f"WITH {oracles.levels(kind).split(', lev AS')[0]} SELECT node_id, parent_id FROM tree",
        )
        # without phase one the helpers of a vertex of k > 2 children are k - 2, whatever the seed
        q[f"bin_size_{kind}"] = (
            lambda spark, d, kind=kind: binary_extension(trees.tree(spark, d, kind), cap=None).agg(F.count(F.lit(1)).alias("n")),
            f"WITH {oracles.levels(kind).split(', lev AS')[0]}, k AS (SELECT count(*) AS k FROM tree WHERE parent_id IS NOT NULL GROUP BY parent_id) SELECT (SELECT count(*) FROM tree) + coalesce((SELECT sum(k - 2)::BIGINT FROM k WHERE k > 2), 0) AS n",
        )
        q[f"bin_valid_{kind}"] = (
            lambda spark, d, kind=kind: _checks(spark, measures.check_binary_extension(trees.tree(spark, d, kind), ready(spark, d, kind).bt)),
            'SELECT true AS "unique", true AS "binary", true AS linear_size, true AS round_trip, true AS origins',
        )
    q["degree_sum_catalog"] = (
        lambda spark, d: measures.degree_sum(trees.catalog(spark, d)),
        f"WITH {oracles.levels('catalog').split(', lev AS')[0]} SELECT count(*) AS vertices, 1::BIGINT AS trees, 2 * (count(*) - 1) AS degree_sum FROM tree",
    )
    # ---- hashing and load ----
    spread, heap_tree = PolyHash(32, seed=1), f"WITH RECURSIVE {oracles.levels('heap').split(', lev AS')[0]}"
    q["hash_distribute_catalog"] = (
        lambda spark, d: distribute(trees.catalog(spark, d), spread).groupBy(F.col("machine").cast("long").alias("machine")).agg(F.count(F.lit(1)).alias("n")),
        f"WITH {oracles.levels('catalog').split(', lev AS')[0]} SELECT {spread.sql('node_id', wide=True)} AS machine, count(*) AS n FROM tree GROUP BY machine",
    )
    q["hash_load_heap"] = (
        lambda spark, d: measures.machine_load(trees.heap(spark, d), spread, "node_w").select(F.col("machine").cast("long").alias("machine"), "load"),
        f"{heap_tree} SELECT {spread.sql('node_id')} AS machine, sum(node_w)::BIGINT AS load FROM tree GROUP BY machine",
    )
    q["hash_uniformity_heap"] = (
        lambda spark, d: measures.hash_uniformity(trees.heap(spark, d), spread).select("machines", "keys", F.round("chi_square", 6).alias("chi_square")),
        f"{heap_tree}, c AS (SELECT {spread.sql('node_id')} AS machine, count(*) AS c FROM tree GROUP BY machine) SELECT 32 AS machines, sum(c)::BIGINT AS keys, round(sum(c * c)::DOUBLE * 32 / sum(c) - sum(c), 6) AS chi_square FROM c",
    )
    q["space_heap"] = (
        lambda spark, d: measures.machine_space(trees.heap(spark, d), spread),
        f"{heap_tree} SELECT {spread.sql('node_id')} AS machine, count(*) AS \"rows\", 48 * count(*) AS bytes FROM tree GROUP BY machine",
    )
    q["traffic_heap"] = (
        lambda spark, d: measures.machine_traffic(trees.heap(spark, d), spread),
        f"""{heap_tree}, ends AS (SELECT {spread.sql('node_id')} AS a, {spread.sql('parent_id')} AS b FROM tree WHERE parent_id IS NOT NULL),
            each AS (SELECT a AS machine, 1 AS sent, 0 AS received FROM ends WHERE a <> b UNION ALL SELECT b, 0, 1 FROM ends WHERE a <> b)
            SELECT machine, sum(sent)::BIGINT AS sent, sum(received)::BIGINT AS received FROM each GROUP BY machine""",
    )
    q["grouped_load_bound_heap"] = (
        lambda spark, d: measures.grouped_load_bound(trees.heap(spark, d), "node_w", 32),
        f"WITH {oracles.levels('heap').split(', lev AS')[0]} SELECT sum(g)::BIGINT AS bound FROM (SELECT max(node_w) AS g FROM (SELECT node_w, (row_number() OVER (ORDER BY node_w) - 1) // 32 AS grp FROM tree) GROUP BY grp)",
    )
    # ---- decomposition ----
    for kind in ("chain_all", "heap", "random", "caterpillar", "catalog", "chain_user"):
        q[f"dec_valid_{kind}"] = (_dec_valid(kind), _DEC_SQL)
    for kind in ("random", "chain_all", "caterpillar"):
        q[f"dec_valid_distributed_{kind}"] = (_dec_valid(kind, local_rows=0), _DEC_SQL)
    # a decomposition of its own: the shared one may have been made by an earlier query
    q["dec_rounds_random"] = (lambda spark, d: measures.decomposition_rounds(prepare_tree(trees.random(spark, d), MACHINES).dec), None)
    q["dec_success_chain_all"] = (lambda spark, d: spark.createDataFrame([(measures.success_share(trees.chain_all(spark, d), MACHINES, 3),)], "share double"), "SELECT 1.0::DOUBLE AS share")
    q["dec_measures_random"] = (
        lambda spark, d: measures.metrics_frame(spark, "run", "decompose", [(0, k, v) for k, v in measures.piece_measures(ready(spark, d, "random").dec).items()]),
        None,
    )
    for kind in ("heap", "random", "catalog"):
        # two-child pieces and leaves of the tree of pieces, and of the whole binary tree
        q[f"dec_leaf_identity_{kind}"] = (
            lambda spark, d, kind=kind: spark.createDataFrame(
                [(measures.leaf_identity(ready(spark, d, kind).dec.comp, "comp_id", "parent_comp"), measures.leaf_identity(ready(spark, d, kind).bt, "node_id", "parent_id"))], "wrong_piece_trees long, wrong_trees long"
            ),
            "SELECT 0::BIGINT AS wrong_piece_trees, 0::BIGINT AS wrong_trees",
        )
    # ---- other small-state problems and variants ----
    extra = {"mids_heap": independent_dominating_set(), "mec_random": edge_cover(), "colour3_random": colouring(3), "domination2_random": r_hop_domination(2)}
    for name, problem in extra.items():
        rule, kind = name.rsplit("_", 1)
        q[name] = (lambda spark, d, kind=kind, problem=problem: solve(ready(spark, d, kind), problem).select("tree_id", "problem", "value"), oracles.answers(kind, rule))
    q["mis_values_per_vertex_heap"] = (lambda spark, d: values_per_vertex(ready(spark, d, "heap"), PROBLEMS["mis"]()), oracles.vertex_values("heap", "mis"))
    q["mis_recovered_weight_heap"] = (
        lambda spark, d: measures.independent_set_weight(trees.heap(spark, d), recover(ready(spark, d, "heap"), PROBLEMS["mis"]())),
        f"SELECT value AS weight, 0::BIGINT AS inner_edges FROM ({oracles.answers('heap', 'mis')})",
    )
    q["mwm_scheduled_random"] = (lambda spark, d: solve(ready(spark, d, "random"), PROBLEMS["mwm"](), finish_by="scheduled").select("tree_id", "problem", "value"), oracles.answers("random", "mwm"))
    q["mwm_comb_random"] = (lambda spark, d: solve(prepare_tree(trees.random(spark, d), MACHINES, shape="comb", seed=5), PROBLEMS["mwm"]()).select("tree_id", "problem", "value"), oracles.answers("random", "mwm"))
    # ---- baselines ----
    for kind, problem in (("chain_user", "mwm"), ("catalog", "mis"), ("heap", "mds"), ("random", "lpath")):
        q[f"base_sequential_{problem}_{kind}"] = (lambda spark, d, kind=kind, problem=problem: baselines.sequential(trees.tree(spark, d, kind), PROBLEMS[problem]()).select("tree_id", "problem", "value"), oracles.answers(kind, problem))
    for kind, problem in (("catalog", "mwm"), ("heap", "mis")):
        q[f"base_levelsync_{problem}_{kind}"] = (lambda spark, d, kind=kind, problem=problem: baselines.level_sync(trees.tree(spark, d, kind), PROBLEMS[problem]()).select("tree_id", "problem", "value"), oracles.answers(kind, problem))
    for kind, problem in (("chain_all", "mwm"), ("chain_user", "mis"), ("chain_user", "mds")):
        q[f"base_path_pieces_{problem}_{kind}"] = (lambda spark, d, kind=kind, problem=problem: baselines.path_pieces(trees.tree(spark, d, kind), PROBLEMS[problem]()).select("tree_id", "problem", "value"), oracles.answers(kind, problem))
    for kind in ("edge", "vertex"):
        q[f"base_random_{kind}_cuts_heap"] = (lambda spark, d, kind=kind: baselines.random_cuts(ready(spark, d, "heap").bt, 32, kind=kind), None)
    q["base_naive_hash_partition_random"] = (lambda spark, d: baselines.naive_partition(trees.random(spark, d), 8), None)
    q["base_naive_range_partition_random"] = (
        lambda spark, d: baselines.naive_partition(trees.random(spark, d), 8, "range"),
        f"""WITH RECURSIVE {oracles.levels('random').split(', lev AS')[0]}, w AS (SELECT min(node_id) AS a, (max(node_id) - min(node_id)) // 8 + 1 AS width FROM tree)
            SELECT count(*) AS edges, count(*) FILTER ((node_id - a) // width <> (parent_id - a) // width) AS cut_edges FROM tree, w WHERE parent_id IS NOT NULL""",
    )
    q["base_no_phase_one_load_star"] = (
        # without phase one, one task gets all children of the centre; with it, about cap of them
        lambda spark, d: spark.createDataFrame(
            [tuple(int(measures.max_children(rows)) for rows in (start(trees.star(spark, d)), cap_degree(start(trees.star(spark, d)), default_cap(trees.star(spark, d).count(), MACHINES))))], "without long, with_cap long"
        ).select("without", (F.col("with_cap") < F.col("without")).alias("smaller")),
        "SELECT count(*) AS without, true AS smaller FROM part",
    )
    q["base_no_below_completed_rule_caterpillar"] = (
        # pieces fall apart: what the rule is for
        lambda spark, d: spark.createDataFrame([(_broken(ready(spark, d, "caterpillar").bt),)], "broken boolean"),
        "SELECT true AS broken",
    )
    q["base_no_coin_chain_all"] = (
        # a whole chain meets in one piece: what the coin is for
        lambda spark, d: decompose(ready(spark, d, "chain_all").bt, MACHINES, rules=Rules(coin=False)).comp.agg(F.max("n_vertices").alias("largest")),
        "SELECT count(*) AS largest FROM events",
    )
    q["base_no_two_child_rule_random"] = (
        # components get more than two children: what the rule is for
        lambda spark, d: spark.createDataFrame([(max(decompose(ready(spark, d, "random").bt, MACHINES, rules=Rules(two_children=False, max_iterations=6)).measure("max_children")) > 2,)], "broken boolean"),
        "SELECT true AS broken",
    )
    q["base_weighted_intervals"] = (
        lambda spark, d: baselines.weighted_intervals(trees.load(spark, d, "events").select("user_id", F.unix_timestamp("ts").alias("s"), (F.unix_timestamp("ts") + 86400).alias("e"), F.lit(1).cast("long").alias("w")), "user_id", "s", "e", "w"),
        # intervals of one length and weight: the earliest that fits, again and again
        """WITH RECURSIVE t AS (SELECT user_id, floor(epoch(ts))::BIGINT AS s FROM events), pick AS (
            SELECT user_id, min(s) AS s, 1::BIGINT AS value FROM t GROUP BY user_id
            UNION ALL SELECT p.user_id, min(t.s), any_value(p.value) + 1 FROM pick p JOIN t ON t.user_id = p.user_id AND t.s >= p.s + 86400 GROUP BY p.user_id, p.s)
            SELECT user_id, max(value) AS value FROM pick GROUP BY user_id""",
    )
    q["base_longest_increasing"] = (
        lambda spark, d: baselines.longest_increasing(trees.load(spark, d, "events").select("user_id", "event_id", "value"), "user_id", "event_id", "value"),
        """WITH RECURSIVE t AS (SELECT user_id, value, row_number() OVER (PARTITION BY user_id ORDER BY event_id) AS i FROM events), run AS (
            SELECT user_id, i, [{'v': value, 'l': 1::BIGINT}] AS seen FROM t WHERE i = 1
            UNION ALL SELECT r.user_id, t.i, list_append(r.seen, {'v': t.value, 'l': 1 + coalesce(list_max(list_transform(list_filter(r.seen, lambda x: x.v < t.value), lambda x: x.l)), 0)})
            FROM run r JOIN t ON t.user_id = r.user_id AND t.i = r.i + 1)
            SELECT user_id, max(list_max(list_transform(seen, lambda x: x.l))) AS length FROM run GROUP BY user_id""",
    )
    # ---- tables that grow with the subtree: a forest of chains, whole, against SQL ----
    chains = lambda spark, d: trees.chain_user(spark, d)
    half = f"WITH RECURSIVE {oracles.chain_profiles('chain_user')} SELECT tree_id, v AS value FROM prof WHERE idx = n // 2"
    q["bisect_chain_user"] = (lambda spark, d: _value(linear.bisection(chains(spark, d), MACHINES)), half)
    q["bisect_profile_chain_user"] = (
        lambda spark, d: linear.solve_vectors(chains(spark, d), linear.BISECTION, MACHINES),
        f"WITH RECURSIVE {oracles.chain_profiles('chain_user')} SELECT tree_id, idx, v AS value FROM prof",
    )
    q["bisect_sequential_chain_user"] = (lambda spark, d: _value(bottom_up.bisection_sequential(chains(spark, d))), half)
    for finish in linear.FINISHES:
        # pieces of about 16 vertices, so that every tree is merged from several; the grid without a local finish
        q[f"bisect_{finish}_chain_user"] = (lambda spark, d, finish=finish: _value(linear.bisection(chains(spark, d), _pieces_of(spark, d, 16), finish=finish, block=32, local_elements=0, rules=Rules(stop_factor=1))), half)
    spans = f"WITH RECURSIVE {oracles.chain_positions('chain_user')}"
    for k in (1, 2, 5, 40):
        for sense in ("min", "max"):
            window = f"SELECT tree_id, i, n, place - lag(place, {k - 1}) OVER (PARTITION BY tree_id ORDER BY i) AS s FROM pos"
            q[f"k{sense}_chain_user_k{k}"] = (
                lambda spark, d, k=k, sense=sense: _value(linear.k_spanning(chains(spark, d), k, sense, MACHINES)),
                f"{spans} SELECT tree_id, {sense}(s)::BIGINT AS value FROM ({window}) GROUP BY tree_id",
            )
    q["kmin_sequential_chain_user"] = (lambda spark, d: _value(bottom_up.k_spanning_sequential(chains(spark, d), 5)), f"{spans} SELECT tree_id, min(s)::BIGINT AS value FROM (SELECT tree_id, place - lag(place, 4) OVER (PARTITION BY tree_id ORDER BY i) AS s FROM pos) GROUP BY tree_id")
    # ---- the bottom-up problems on forests of chains and of customers' orders and lines ----
    for kind in ("chain_user", "customers"):
        forest = lambda spark, d, kind=kind: trees.tree(spark, d, kind)
        q[f"kcenter_{kind}"] = (lambda spark, d, f=forest: _value(bottom_up.k_center(f(spark, d), 2)), oracles.served(kind, "max"))
        q[f"kmedian_{kind}"] = (lambda spark, d, f=forest: _value(bottom_up.k_median(f(spark, d), 2)), oracles.served(kind, "sum"))
        q[f"mindiam_{kind}"] = (lambda spark, d, f=forest: _value(bottom_up.minimum_diameter(f(spark, d), 5)), oracles.least_diameter(kind, 5))
        q[f"ufl_{kind}"] = (lambda spark, d, f=forest: _value(bottom_up.facility_location(f(spark, d))), oracles.chain_facilities(kind) if kind == "chain_user" else None)
        parts = "ceil(count(*) / 10)" if kind == "chain_user" else None
        q[f"kpart_{kind}"] = (lambda spark, d, f=forest: _value(bottom_up.k_partition(f(spark, d), 10)), f"WITH RECURSIVE {oracles.levels(kind)} SELECT tree_id, {parts}::BIGINT AS value FROM tree GROUP BY tree_id" if parts else None)
    for name, run in (("bisect", linear.bisection), ("bisect_sequential", bottom_up.bisection_sequential)):
        q[f"{name}_customers"] = (lambda spark, d, run=run: _value(run(trees.customers(spark, d))), None)
    # ---- single trees over all events; bisection has no SQL here, as its tables are quadratic ----
    for kind in ("chain_all", "heap"):
        q[f"bisect_{kind}"] = (lambda spark, d, kind=kind: _value(linear.bisection(trees.tree(spark, d, kind), WHOLE_MACHINES)), None)
        q[f"bisect_sequential_{kind}"] = (lambda spark, d, kind=kind: _value(bottom_up.bisection_sequential(trees.tree(spark, d, kind))), None)
        q[f"bisect_grid_{kind}"] = (lambda spark, d, kind=kind: _value(linear.bisection(trees.tree(spark, d, kind), WHOLE_MACHINES, local_elements=0)), None)
    q["bisect_profile_chain_all"] = (lambda spark, d: linear.solve_vectors(trees.chain_all(spark, d), linear.BISECTION, WHOLE_MACHINES).select("idx", "value"), None)
    for finish in linear.FINISHES[1:]:
        q[f"bisect_{finish}_chain_all"] = (lambda spark, d, finish=finish: _value(linear.bisection(trees.chain_all(spark, d), WHOLE_MACHINES, finish=finish)), None)
    for k in (1, 2, 5, 1000):
        window = f"SELECT sum(edge_w) OVER (ORDER BY node_id ROWS BETWEEN {max(0, k - 2)} PRECEDING AND CURRENT ROW) AS s, node_id FROM tree"
        for sense in ("min", "max"):
            inner = f"SELECT {sense}(s)::BIGINT AS value FROM ({window}) WHERE node_id >= {k - 1}" if k > 1 else "SELECT 0::BIGINT AS value"
            q[f"k{sense}_chain_all_k{k}"] = (
                lambda spark, d, k=k, sense=sense: _value(linear.k_spanning(trees.chain_all(spark, d), k, sense, WHOLE_MACHINES)),
                f"WITH {oracles.levels('chain_all')} SELECT 0::BIGINT AS tree_id, value FROM ({inner})",
            )
    q["kmin_heap"] = (lambda spark, d: _value(linear.k_spanning(trees.heap(spark, d), 5, "min", WHOLE_MACHINES)), None)
    q["kmin_sequential_heap"] = (lambda spark, d: _value(bottom_up.k_spanning_sequential(trees.heap(spark, d), 5)), None)
    q["kcenter_heap"] = (lambda spark, d: _value(bottom_up.k_center(trees.heap(spark, d), 2)), None)
    q["kcenter_mst"] = (lambda spark, d: _value(bottom_up.k_center(ready_tree(spark, d, "mst"), 3)), None)
    q["kpart_chain_all"] = (lambda spark, d: _value(bottom_up.k_partition(trees.chain_all(spark, d), 10)), "SELECT 0::BIGINT AS tree_id, ceil(count(*) / 10)::BIGINT AS value FROM events")
    # ---- schedule ----
    q["schedule_rows_random"] = (lambda spark, d: measures.schedule_rows(schedule.build(ready(spark, d, "random").dec.comp)), None)
    q["merge_work_heap"] = (lambda spark, d: _merge_work(ready(spark, d, "heap")), None)
    # ---- streams run over all that is there ----
    q["stream_purchases_after_views"] = (
        lambda spark, d: run_available(purchases_after_views(events_stream(spark, d, "1 hour")), scratch_folder(spark, "stream")),
        """SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase'
           AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR""",
    )
    q["stream_join_static"] = (
        lambda spark, d: run_available(join_static(events_stream(spark, d), trees.load(spark, d, "customer")).select("event_id", "user_id", "c_mktsegment"), scratch_folder(spark, "stream")),
        "SELECT event_id, user_id, c_mktsegment FROM events LEFT JOIN customer ON c_custkey = user_id",
    )
    q["stream_dedup_events"] = (lambda spark, d: run_available(dedup_events(events_stream(spark, d)).select("event_id"), scratch_folder(spark, "stream")), "SELECT DISTINCT event_id FROM events")
    # ---- streaming: the online chain problem gives the batch answer ----
    q["stream_chain_mis_batch"] = (lambda spark, d: batch_chain(trees.load(spark, d, "events"), PROBLEMS["mis"]()), f"SELECT tree_id AS user_id, value FROM ({oracles.answers('chain_user', 'mis')})")
    return q


def _registered() -> dict[str, tuple[Query, str | None]]:
    return _method_queries() | OPS


def queries() -> dict[str, Query]:
    return {name: run for name, (run, _) in _registered().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _registered().items() if sql}
