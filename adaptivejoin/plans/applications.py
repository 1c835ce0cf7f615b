"""Applications: entity annotation, multi-joins, parameters, read alignment, and the store's own queries."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adaptivejoin.functions.costs import CostProfile
from adaptivejoin.functions.hashing import portable_hash, row_id
from adaptivejoin.operators import joins, routing
from adaptivejoin.operators.joins import CallSpec, Stage
from adaptivejoin.operators.routing import Access
from adaptivejoin.plans import core
from adaptivejoin.plans import sqltext as S
from adaptivejoin.plans import workloads as X
from adaptivejoin.sources import store as st
from adaptivejoin.sources.prefetch import AccessMode, prefetch_map
from adaptivejoin.tables import table

QUERIES: dict = {}
ORACLES: dict = {}
CONTEXT, DIMS, MOST_CANDIDATES = 5, 64, 8


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


# Annotation: tokens that a dictionary knows, with their context, get the entity whose model scores highest.


def word_array(text):
    return F.regexp_extract_all(F.lower(F.coalesce(text, F.lit(""))), F.lit("[a-z]+"), F.lit(0))


def dictionary(spark, folder) -> DataFrame:
    return table(spark, folder, "benchmark").select(F.explode(word_array(F.col("text"))).alias("token")).where("length(token) >= 4").distinct()


def tokens(docs: DataFrame, ids: tuple[str, ...]) -> DataFrame:
    """(ids, pos, token, ctx): every token with up to five on each side. Contexts are cut within the row, so that no token carries
    the words of its whole text."""
    ws = docs.select(*ids, word_array(F.col("text")).alias("ws"))

    def window(token, i):
        lo = F.greatest(F.lit(1), i + 1 - CONTEXT)
        return F.struct(i.alias("pos"), token.alias("token"), F.slice("ws", lo, F.least(F.size("ws"), i + 1 + CONTEXT) - lo + 1).alias("ctx"))

    return ws.select(*ids, F.inline(F.transform("ws", window)))


def spots(spark, folder, docs: DataFrame, ids: tuple[str, ...]) -> DataFrame:
    """Tokens of the dictionary. Its size is that of a word list; the planner broadcasts it only if it is small."""
    return tokens(docs, ids).join(dictionary(spark, folder), "token", "left_semi")


def models(spark, folder) -> DataFrame:
    """(token, cand, entity, weights): 1 to 8 candidates of each dictionary word, with fixed-point weights."""
    h = portable_hash(F.col("token"))
    n = table(spark, folder, "embeddings").count()
    cands = dictionary(spark, folder).withColumn("i", F.explode(F.sequence(F.lit(0).cast("long"), h % MOST_CANDIDATES)))
    cands = cands.withColumn("entity", portable_hash(F.concat_ws("#", "token", F.col("i").cast("string"))) % n)
    vectors = table(spark, folder, "embeddings").select(F.col("vec_id").alias("entity"), F.transform("embedding", lambda x: F.floor(x.cast("double") * 1024).cast("long")).alias("weights"))
    return cands.join(vectors, "entity").select("token", "entity", "weights").distinct()


def scored(spots_: DataFrame, models_: DataFrame, ids: tuple[str, ...]) -> DataFrame:
    """Best entity of each spot: the sum of the weights at the hashed places of the context words; ties to the smaller entity.

    A token's candidates travel as one value, so that the annotation is a keyed call on the token.
    """
    return chosen(placed(spots_).join(model_store(models_), "token").withColumn("best", best_entity()), ids)


def model_store(models_: DataFrame) -> DataFrame:
    """(token, cands, value_bytes): the models of a token as one stored value."""
    return models_.groupBy("token").agg(F.collect_list(F.struct("entity", "weights")).alias("cands"), (F.count("*") * 8 * (DIMS + 1)).alias("value_bytes"))


def placed(spots_: DataFrame) -> DataFrame:
    """Spots with the places of their context words: the parameters of the call."""
    return spots_.withColumn("places", F.transform("ctx", lambda w: (portable_hash(w) % DIMS + 1).cast("int"))).drop("ctx")


def best_entity():
    score = lambda c: F.aggregate("places", F.lit(0).cast("long"), lambda a, p: a + F.element_at(c["weights"], p))
    return F.array_max(F.transform("cands", lambda c: F.struct(score(c).alias("score"), (-c["entity"]).alias("minus"))))


def chosen(rows: DataFrame, ids: tuple[str, ...]) -> DataFrame:
    return rows.select(*ids, "pos", "token", (-F.col("best.minus")).alias("entity"), F.col("best.score").alias("score"))


WORDS = "regexp_extract_all(lower(coalesce(text, '')), '[a-z]+')"
DICT = f"dict AS (SELECT DISTINCT token FROM (SELECT unnest({WORDS}) AS token FROM benchmark) WHERE length(token) >= 4)"


def _spots_sql(rel: str, ids: str) -> str:
    return f"""{DICT}, ws AS (SELECT {ids}, {WORDS} AS ws FROM {rel}), at_ AS (SELECT {ids}, ws, unnest(ws) AS token, generate_subscripts(ws, 1) - 1 AS pos FROM ws),
spots AS (SELECT {ids}, CAST(pos AS INTEGER) AS pos, token, ws[greatest(1, pos + 1 - {CONTEXT}) : pos + 1 + {CONTEXT}] AS ctx FROM at_ WHERE token IN (SELECT token FROM dict))"""


MODELS = f"""cands AS (SELECT token, unnest(range(0, {S.h('token')} % {MOST_CANDIDATES} + 1)) AS i FROM dict),
chosen AS (SELECT DISTINCT token, {S.h("token || '#' || i")} % (SELECT count(*) FROM embeddings) AS entity FROM cands),
models AS (SELECT token, entity, list_transform(embedding, lambda x: CAST(floor(CAST(x AS DOUBLE) * 1024) AS BIGINT)) AS weights FROM chosen JOIN embeddings ON entity = vec_id)"""


def _scored_sql(ids: str) -> str:
    return f"""scores AS (SELECT {ids}, pos, s.token, entity, CAST(list_sum(list_transform(ctx, lambda w: weights[{S.h('w')} % {DIMS} + 1])) AS BIGINT) AS score FROM spots s JOIN models m ON s.token = m.token),
ranked AS (SELECT *, row_number() OVER (PARTITION BY {ids}, pos ORDER BY score DESC, entity) AS r FROM scores)"""


@query("annotate_spots", f"WITH {_spots_sql('documents', 'doc_id')} SELECT doc_id, pos, token, array_to_string(ctx, ' ') AS ctx FROM spots")
def annotate_spots(spark, folder):
    return spots(spark, folder, table(spark, folder, "documents"), ("doc_id",)).select("doc_id", "pos", "token", F.array_join("ctx", " ").alias("ctx"))


@query("annotate_entities", f"WITH {_spots_sql('documents', 'doc_id')}, {MODELS}, {_scored_sql('doc_id')} SELECT doc_id, pos, token, entity, score FROM ranked WHERE r = 1")
def annotate_entities(spark, folder):
    return scored(spots(spark, folder, table(spark, folder, "documents"), ("doc_id",)), models(spark, folder), ("doc_id",))


@query("annotate_top_tokens", f"WITH {_spots_sql('documents', 'doc_id')} SELECT token, count(*) AS n FROM spots GROUP BY token ORDER BY n DESC, token LIMIT 20")
def annotate_top_tokens(spark, folder):
    return spots(spark, folder, table(spark, folder, "documents"), ("doc_id",)).groupBy("token").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "token").limit(20)


ENTITIES = ORACLES["annotate_entities"]
ANNOTATION = CallSpec(("cands",), best_entity, "best")


def annotated_by(name: str, lanes: int = 8):
    """Annotation as a keyed join under one of the strategies; all of them give the same entities."""

    def add(join):
        @query(f"annotate_{name}", ENTITIES)
        def annotate(spark, folder):
            rows = placed(spots(spark, folder, table(spark, folder, "documents"), ("doc_id",)))
            rows = st.spooled(routing.assign_lanes(rows, lanes, F.col("doc_id")), "spots")
            stored = st.spooled(model_store(models(spark, folder)).withColumnRenamed("token", "skey"), "models")
            return chosen(join(rows, stored), ("doc_id",))

        return join

    return add


SPOT = Access("token", "lane", ("doc_id", "pos"))


def _best(row: dict, value: tuple | None) -> dict | None:
    """``best_entity`` of one row, where its lane computes it."""
    if value is None:
        return None
    scored = []
    for c in value[0]:
        picked = [c["weights"][p - 1] for p in row["places"]] if c["weights"] is not None else [None]
        known = None not in picked
        scored.append((known, sum(picked) if known else 0, -c["entity"]))
    known, score, minus = max(scored)
    return {"doc_id": row["doc_id"], "pos": row["pos"], "token": row["token"], "best": {"score": score if known else None, "minus": minus}}


def fetched_in_batches(rows: DataFrame, stored: DataFrame, homes: int = 8) -> DataFrame:
    """Spots are dealt to their lanes, which fetch models from the store in batches ahead of need and keep none of them: a value goes
    from the store to the lane that computes with it, and never through a shuffle."""
    path = st.shared_path(rows.sparkSession, "model-store")
    st.build_store(stored.select("skey", "cands"), "skey", homes, path, st.CALL_BLOCK)
    dealt = rows.select("lane", "doc_id", "pos", "token", "places").repartition("lane")
    connect = lambda: st.FileStore(path, "skey", homes, ("cands",), st.CALL_BLOCKS)
    return prefetch_map(dealt, "token", connect, _best, "doc_id long, pos int, token string, best struct<score: long, minus: long>", AccessMode("async", 256, 4))


@annotated_by("batched_fetch")
def annotate_batched_fetch(rows, stored):
    return fetched_in_batches(rows, stored)


@annotated_by("always_ship")
def annotate_always_ship(rows, stored):
    return joins.ship_join(rows, stored, "token", "skey", ANNOTATION)


@annotated_by("coin_flip")
def annotate_coin_flip(rows, stored):
    coin = F.pmod(portable_hash(F.concat_ws("-", "doc_id", "pos")), F.lit(2))
    far = joins.ship_join(rows.where(coin == 0), stored, "token", "skey", ANNOTATION).select("doc_id", "pos", "token", "best")
    return far.unionByName(fetched_in_batches(rows.where(coin == 1), stored))


@annotated_by("adaptive")
def annotate_adaptive(rows, stored):
    p = CostProfile(home_cpu_us=48, lane_cpu_us=20)
    routed = routing.online_route(rows, stored, SPOT, "skey", "value_bytes", p.rent(), p.buy(F.col("value_bytes")), p.use_memory())
    return joins.adaptive_join(routed, stored, SPOT, "skey", ANNOTATION)


@annotated_by("plain_reduce")
def annotate_plain_reduce(rows, stored):
    return joins.keyed_join(rows, stored, "token", "skey", ANNOTATION, hint="shuffle_hash")


@annotated_by("full_stats_heavy_hitter")
def annotate_full_stats_heavy_hitter(rows, stored):
    return joins.heavy_hitter_join(rows, stored, "token", "skey", ANNOTATION, F.count("*"), max(1, rows.count() // 100))


@annotated_by("cost_aware_replicate")
def annotate_cost_aware_replicate(rows, stored):
    """A call costs as many scores as its token has candidates."""
    costs = rows.groupBy("token").agg(F.count("*").alias("n")).join(stored.select("skey", F.size("cands").alias("k")), F.col("token") == F.col("skey"))
    least = max(1, (costs.agg(F.sum(F.col("n") * F.col("k"))).first()[0] or 0) // 100)
    known = rows.join(stored.select(F.col("skey").alias("of"), F.size("cands").alias("scores")), F.col("token") == F.col("of"), "left").drop("of")
    return joins.heavy_hitter_join(known, stored, "token", "skey", ANNOTATION, F.sum("scores"), least)


@query("annotate_index", f"WITH {_spots_sql('documents', 'doc_id')}, {MODELS}, {_scored_sql('doc_id')} SELECT entity, count(*) AS mentions, count(DISTINCT doc_id) AS docs FROM ranked WHERE r = 1 GROUP BY entity")
def annotate_index(spark, folder):
    """The step after annotation: an index by entity."""
    return annotate_entities(spark, folder).groupBy("entity").agg(F.count("*").alias("mentions"), F.countDistinct("doc_id").alias("docs"))


@query("annotate_routes", f"WITH {_spots_sql('documents', 'doc_id')}, n AS (SELECT {S.h('CAST(doc_id AS VARCHAR)')} % 8 AS lane, token, count(*) AS n FROM spots GROUP BY 1, 2) SELECT token, CAST(sum(least(n, 3)) AS BIGINT) AS ship, count(*) FILTER (n > 3) AS fetch, CAST(sum(greatest(n - 4, 0)) AS BIGINT) AS local FROM n GROUP BY token")
def annotate_routes(spark, folder):
    """Annotation routed by token: rare models stay with their owners, frequent ones are fetched to the documents' lanes."""
    rows = spots(spark, folder, table(spark, folder, "documents"), ("doc_id",)).select("doc_id", "pos", "token")
    lanes = routing.assign_lanes(rows, 8, F.col("doc_id"))
    routed = routing.ski_route(lanes, Access("token", "lane", ("doc_id", "pos")), F.lit(40), F.lit(60), F.lit(20))
    n = lambda r: F.count_if(F.col("route") == r).alias(r)
    return routed.groupBy("token").agg(n("ship"), n("fetch"), n("local"))


@query("annotate_messages_share", f"WITH {_spots_sql('conversations', 'conv_id, turn')}, hit AS (SELECT DISTINCT conv_id, turn FROM spots) SELECT (SELECT count(*) FROM conversations) AS messages, (SELECT count(*) FROM hit) AS annotated")
def annotate_messages_share(spark, folder):
    msgs = table(spark, folder, "conversations")
    hit = spots(spark, folder, msgs, ("conv_id", "turn")).select("conv_id", "turn").distinct().agg(F.count("*").alias("annotated"))
    return msgs.agg(F.count("*").alias("messages")).crossJoin(F.broadcast(hit))


# Chains of joins


def _part(spark, folder):
    return Stage(table(spark, folder, "part"), "p_partkey", "l_partkey", CallSpec(("p_brand", "p_type"), lambda: F.struct("p_brand", "p_type"), "part"))


def _supplier(spark, folder):
    return Stage(table(spark, folder, "supplier"), "s_suppkey", "l_suppkey", CallSpec(("s_nationkey",), lambda: F.col("s_nationkey"), "nationkey"))


def _nation(spark, folder):
    return Stage(table(spark, folder, "nation"), "n_nationkey", "nationkey", CallSpec(("n_name", "n_regionkey"), lambda: F.struct("n_name", "n_regionkey"), "nation"))


def _orders(spark, folder):
    return Stage(table(spark, folder, "orders"), "o_orderkey", "l_orderkey", CallSpec(("o_custkey",), lambda: F.col("o_custkey"), "custkey"))


def _customer(spark, folder):
    return Stage(table(spark, folder, "customer"), "c_custkey", "custkey", CallSpec(("c_nationkey",), lambda: F.col("c_nationkey"), "nationkey"))


REVENUE = "CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DECIMAL(38,2))"


def revenue():
    return F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("decimal(38,2)").alias("revenue")


def _chain(spark, folder, stages, where: str = "true", shuffle: bool = False) -> DataFrame:
    rows = table(spark, folder, "lineitem").where(where).select(*X.SEQ, "l_extendedprice", "l_shipdate")
    if shuffle:
        return joins.chain_shuffle(rows, stages)
    return joins.chain_join(rows, stages, S.LANES, row_id(*X.SEQ), X.SEQ)


TWO = f"SELECT p_brand, {REVENUE} AS revenue FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY p_brand"
THREE = f"SELECT n_name, {REVENUE} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"
FILTERED = f"SELECT n_name, {REVENUE} AS revenue FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey WHERE p_type LIKE '%A%' AND l_shipdate >= TIMESTAMP '1996-01-01' GROUP BY n_name"
FOUR = f"SELECT r_name, {REVENUE} AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name HAVING {REVENUE} > 1000 ORDER BY revenue DESC LIMIT 3"


@query("chain_two", TWO)
def chain_two(spark, folder):
    return _chain(spark, folder, [_part(spark, folder), _supplier(spark, folder)]).groupBy("part.p_brand").agg(revenue())


@query("chain_three", THREE)
def chain_three(spark, folder):
    return _chain(spark, folder, [_orders(spark, folder), _customer(spark, folder), _nation(spark, folder)]).groupBy("nation.n_name").agg(revenue())


@query("chain_filtered", FILTERED)
def chain_filtered(spark, folder):
    """Selections before the joins; the value columns are pruned to those that the calls name."""
    from dataclasses import replace

    part = _part(spark, folder)
    part = replace(part, stored=part.stored.where(F.col("p_type").like("%A%")))
    rows = _chain(spark, folder, [part, _supplier(spark, folder), _nation(spark, folder)], "l_shipdate >= timestamp_ntz'1996-01-01'")
    return rows.groupBy("nation.n_name").agg(revenue())


@query("chain_four", FOUR)
def chain_four(spark, folder):
    """Four joins, then the SQL operators after them."""
    region = Stage(table(spark, folder, "region"), "r_regionkey", "nation.n_regionkey", CallSpec(("r_name",), lambda: F.col("r_name"), "r_name"))
    out = _chain(spark, folder, [_orders(spark, folder), _customer(spark, folder), _nation(spark, folder), region])
    return out.groupBy("r_name").agg(revenue()).where("revenue > 1000").orderBy(F.desc("revenue")).limit(3)


@query("strategy_staged_reduce_chain_result", THREE)
def staged_reduce_chain(spark, folder):
    return _chain(spark, folder, [_orders(spark, folder), _customer(spark, folder), _nation(spark, folder)], shuffle=True).groupBy("nation.n_name").agg(revenue())


@query("chain_sql_engine", THREE)
def chain_sql_engine(spark, folder):
    for n in ("lineitem", "orders", "customer", "nation"):
        table(spark, folder, n).createOrReplaceTempView(f"chain_{n}")
    return spark.sql("SELECT n_name, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DECIMAL(38,2)) AS revenue FROM chain_lineitem JOIN chain_orders ON l_orderkey = o_orderkey JOIN chain_customer ON o_custkey = c_custkey JOIN chain_nation ON c_nationkey = n_nationkey GROUP BY n_name")


def _home(c: str) -> str:
    return f"CAST({S.h(f'CAST({c} AS VARCHAR)')} % {S.HOMES} AS INTEGER)"


@query("chain_combined_load", f"WITH x AS (SELECT {_home('l_partkey')} AS home FROM lineitem UNION ALL SELECT {_home('l_suppkey')} FROM lineitem) SELECT home, count(*) AS calls FROM x GROUP BY home")
def chain_combined_load(spark, folder):
    """Calls that reach each owner over the stages of a chain together."""
    li = table(spark, folder, "lineitem")
    both = li.select(F.col("l_partkey").alias("k")).unionAll(li.select(F.col("l_suppkey").alias("k")))
    return routing.assign_home(both, "k", S.HOMES).groupBy("home").agg(F.count("*").alias("calls"))


# The store, prefetching, parameters


@query("store_build_roundtrip", f"SELECT {_home('p_partkey')} AS home, count(*) AS n, CAST(sum(p_partkey) AS BIGINT) AS total FROM part GROUP BY 1")
def store_build_roundtrip(spark, folder):
    built = st.build_store(table(spark, folder, "part"), "p_partkey", S.HOMES, st.shared_path(spark, "store"))
    return built.groupBy(F.col("home").cast("int").alias("home")).agg(F.count("*").alias("n"), F.sum("p_partkey").alias("total"))


RESULT_BY_KEY = f"SELECT key, count(*) AS n, CAST(sum(result) AS BIGINT) AS total FROM ({core.PLAIN}) GROUP BY key"


def _prefetched(mode: AccessMode):
    return lambda spark, folder: st.client_join(spark, folder, mode).groupBy("key").agg(F.count("*").alias("n"), F.sum("result").alias("total"))


query("prefetch_pipeline", RESULT_BY_KEY)(_prefetched(AccessMode("async", 256, 4)))
query("prefetch_single_calls", RESULT_BY_KEY)(_prefetched(AccessMode("async", 1, 8)))
query("prefetch_compute_requests", RESULT_BY_KEY)(lambda spark, folder: st.shipped_join(spark, folder, AccessMode("async", 256, 4)).groupBy("key").agg(F.count("*").alias("n"), F.sum("result").alias("total")))


@query("param_pull", "SELECT vec_id, label, CAST(floor(CAST(embedding[1] AS DOUBLE) * 1024) AS BIGINT) AS w FROM embeddings WHERE vec_id BETWEEN 100 AND 199")
def param_pull(spark, folder):
    """A range of keys; the filter reaches the scan."""
    return table(spark, folder, "embeddings").where(F.col("vec_id").between(100, 199)).select("vec_id", "label", F.floor(F.element_at("embedding", 1).cast("double") * 1024).cast("long").alias("w"))


@query("param_push", "WITH upd AS (SELECT event_id % 500 AS k, CAST(sum(CAST(floor(value * 16) AS BIGINT)) AS BIGINT) AS delta FROM events GROUP BY 1) SELECT vec_id, CAST(floor(CAST(embedding[1] AS DOUBLE) * 1024) AS BIGINT) + coalesce(delta, 0) AS w FROM embeddings LEFT JOIN upd ON vec_id = k")
def param_push(spark, folder):
    """Updates, summed before they travel, are added to the parameters of their keys."""
    upd = table(spark, folder, "events").groupBy((F.col("event_id") % 500).alias("k")).agg(F.sum(F.floor(F.col("value") * 16).cast("long")).alias("delta"))
    own = table(spark, folder, "embeddings").select("vec_id", F.floor(F.element_at("embedding", 1).cast("double") * 1024).cast("long").alias("w"))
    return own.join(upd, F.col("vec_id") == F.col("k"), "left").select("vec_id", (F.col("w") + F.coalesce("delta", F.lit(0))).alias("w"))


GRAM = 12


@query("read_alignment", f"""WITH d AS (SELECT doc_id, {WORDS} AS ws FROM documents), dg AS (SELECT doc_id, array_to_string(ws[i : i + {GRAM - 1}], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - {GRAM - 2})) AS i FROM d WHERE len(ws) >= {GRAM})),
b AS (SELECT item_id, {WORDS} AS ws FROM benchmark), bg AS (SELECT item_id, array_to_string(ws[i : i + {GRAM - 1}], ' ') AS g FROM (SELECT item_id, ws, unnest(range(1, len(ws) - {GRAM - 2})) AS i FROM b WHERE len(ws) >= {GRAM})),
hit AS (SELECT doc_id, item_id, count(DISTINCT dg.g) AS shared FROM dg JOIN bg ON dg.g = bg.g GROUP BY doc_id, item_id)
SELECT doc_id, item_id, shared, CAST((SELECT len(ws) FROM b WHERE b.item_id = hit.item_id) - {GRAM - 1} - shared AS BIGINT) AS missing FROM hit QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY shared DESC, item_id) = 1""")
def read_alignment(spark, folder):
    """Seeds of twelve words join documents with passages; the passage that shares most wins, with the seeds it misses."""
    from pyspark.sql import Window as W

    def grams(name: str, key: str) -> DataFrame:
        ws = table(spark, folder, name).select(key, word_array(F.col("text")).alias("ws")).where(F.size("ws") >= GRAM)
        at = ws.select(key, F.size("ws").alias("size"), "ws", F.explode(F.sequence(F.lit(1), F.size("ws") - GRAM + 1)).alias("i"))
        return at.select(key, "size", F.array_join(F.slice("ws", F.col("i"), GRAM), " ").alias("g")).distinct()

    hit = grams("documents", "doc_id").drop("size").join(grams("benchmark", "item_id"), "g").groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"), F.max("size").alias("size"))
    best = hit.withColumn("r", F.row_number().over(W.partitionBy("doc_id").orderBy(F.desc("shared"), "item_id"))).where("r = 1")
    return best.select("doc_id", "item_id", "shared", (F.col("size") - GRAM + 1 - F.col("shared")).cast("long").alias("missing"))


# Sources and sinks


@query("op_scan_bucketed", "SELECT count(*) AS n, CAST(sum(p_size) AS BIGINT) AS total FROM lineitem JOIN part ON l_partkey = p_partkey")
def op_scan_bucketed(spark, folder):
    """The stored side is bucketed and sorted by key once; joins with it then deal only the probe."""
    path = st.shared_path(spark, "bucketed")
    name = "bucketed_part_" + path.rsplit("-", 1)[1]
    table(spark, folder, "part").select("p_partkey", "p_size").write.bucketBy(8, "p_partkey").sortBy("p_partkey").option("path", path).saveAsTable(name)
    return table(spark, folder, "lineitem").select("l_partkey").join(spark.table(name).hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).agg(F.count("*").alias("n"), F.sum("p_size").alias("total"))


@query("op_scan_partition_pruned", "SELECT count(*) AS n FROM orders WHERE o_orderkey % 8 = 3")
def op_scan_partition_pruned(spark, folder):
    path = st.shared_path(spark, "partitioned")
    table(spark, folder, "orders").withColumn("lane", (F.col("o_orderkey") % 8).cast("int")).repartition("lane").write.partitionBy("lane").parquet(path)
    return spark.read.parquet(path).where("lane = 3").agg(F.count("*").alias("n"))


@query("op_formats_roundtrip", "SELECT f, n_nationkey, n_name FROM nation, (VALUES ('csv'), ('json'), ('orc'), ('parquet'), ('text')) v(f)")
def op_formats_roundtrip(spark, folder):
    nation = table(spark, folder, "nation").select("n_nationkey", "n_name")
    out = None
    for f in ("csv", "json", "orc", "parquet"):
        path = st.shared_path(spark, f)
        nation.write.format(f).save(path)
        one = spark.read.format(f).schema(nation.schema).load(path).select(F.lit(f).alias("f"), "n_nationkey", "n_name")
        out = one if out is None else out.unionAll(one)
    path = st.shared_path(spark, "text")
    nation.select(F.concat_ws("\t", F.col("n_nationkey").cast("string"), "n_name")).write.text(path)
    parts = F.split("value", "\t")
    return out.unionAll(spark.read.text(path).select(F.lit("text").alias("f"), parts[0].cast("int").alias("n_nationkey"), parts[1].alias("n_name")))


@query("op_observe", "SELECT count(*) AS n, CAST(sum(l_partkey) AS BIGINT) AS keys FROM lineitem")
def op_observe(spark, folder):
    """Figures taken while the rows pass, without a pass of their own."""
    from pyspark.sql import Observation

    seen = Observation("passing")
    rows = table(spark, folder, "lineitem").select("l_partkey").observe(seen, F.count("*").alias("n"), F.sum("l_partkey").alias("keys"))
    rows.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["n"], seen.get["keys"])], "n long, keys long")


@query("op_datasource_store", f"SELECT CAST({S.h('CAST(o_orderkey AS VARCHAR)')} % 4 AS INTEGER) AS home, count(*) AS n, CAST(sum(o_custkey) AS BIGINT) AS total FROM orders WHERE o_orderkey IS NOT NULL GROUP BY 1")
def op_datasource_store(spark, folder):
    """The orders as a keyed store, read back through its data source; a store has no null keys."""
    path = st.shared_path(spark, "store")
    st.build_store(table(spark, folder, "orders").where("o_orderkey is not null").select("o_orderkey", "o_custkey"), "o_orderkey", 4, path)
    spark.dataSource.register(st.KeyedStoreSource)
    stored = spark.read.format("keyed_store").option("path", path).option("homes", 4).option("key", "o_orderkey").option("value", "o_custkey").load()
    return stored.groupBy("home").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


