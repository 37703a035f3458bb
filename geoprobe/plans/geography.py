"""Queries on sampling, splitting and spatial entanglement over `events`, with their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scalars import hash01_sql, haversine_sql, rounded, rounded_sql, seeded
from ..operators import duplicates, sampling, spatial
from ..session import checkpointed, swept, tables_written
from ..sources.tables import CAPTURES_SQL, captures, load, region_dim

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def register(sql: str | None = None):
    def keep(fn):
        QUERIES[fn.__name__] = fn
        if sql:
            ORACLE_SQL[fn.__name__] = sql
        return fn

    return keep


def split_rows(spark: SparkSession, sf_dir: str, eligible: str = "true") -> DataFrame:
    """The sampled captures with their split: drawn once and written, as the steps after it read it several times."""
    mark = tables_written()
    sample = checkpointed(sampling.density_sample(captures(spark, sf_dir, eligible)))
    return swept(checkpointed(sampling.stratified_split(sample)), mark)


def chain(where: str = "true") -> str:
    """Common table expressions from captures to split rows, as SQL."""
    return f"""WITH {CAPTURES_SQL},
pool AS (SELECT * FROM captures WHERE {where}),
density AS (SELECT region, area, count(*) AS n, count(*) / area AS density FROM pool GROUP BY region, area),
quota AS (SELECT region, n, area, density, least(n, floor((SELECT min(density) FROM density) * area + 0.5)::BIGINT) AS quota FROM density),
sampled AS (SELECT p.*, q.quota, q.n AS pool FROM (SELECT *, row_number() OVER (PARTITION BY region ORDER BY {hash01_sql("'42|s|' || image_id")}, image_id) AS r FROM pool) p JOIN quota q USING (region) WHERE r <= q.quota),
ranked AS (SELECT *, row_number() OVER (PARTITION BY region ORDER BY {hash01_sql("'42|p|' || image_id")}, image_id) AS sr, count(*) OVER (PARTITION BY region) AS size FROM sampled),
rows AS (SELECT *, CASE WHEN sr <= floor(size * 0.7::DOUBLE) THEN 'train' WHEN sr <= floor(size * 0.85::DOUBLE) THEN 'val' ELSE 'test' END AS split FROM ranked),
train_sites AS (SELECT DISTINCT site, region, lat AS lat2, lon AS lon2 FROM rows WHERE split = 'train'),
near AS (SELECT DISTINCT t.image_id FROM rows t JOIN train_sites s ON abs(t.lat - s.lat2) < 0.001 AND abs(t.lon - s.lon2) < 0.001 WHERE t.split = 'test' AND {haversine_sql("t.lat", "t.lon", "s.lat2", "s.lon2")} <= 0.05),
centres AS (SELECT region, avg(lat) AS c_lat, avg(lon) AS c_lon FROM rows WHERE split = 'train' GROUP BY region)
"""


@register(chain() + "SELECT region, count(*)::BIGINT AS n FROM pool GROUP BY region")
def pool_counts(spark, sf_dir):
    return captures(spark, sf_dir).groupBy("region").agg(F.count("*").alias("n"))


@register(chain() + f"SELECT region, n::BIGINT AS n, {rounded_sql('density')} AS density FROM density")
def region_density(spark, sf_dir):
    return sampling.region_density(captures(spark, sf_dir)).select("region", "n", rounded(F.col("density")).alias("density"))


@register(chain() + f"SELECT {rounded_sql('min(density)')} AS common, arg_min(region, density) AS binding_region FROM density")
def common_density(spark, sf_dir):
    return sampling.common_density(sampling.region_density(captures(spark, sf_dir))).select(rounded(F.col("common")).alias("common"), "binding_region")


@register(chain() + "SELECT region, n::BIGINT AS n, quota FROM quota")
def density_quota(spark, sf_dir):
    return sampling.quotas(sampling.region_density(captures(spark, sf_dir))).select("region", "n", "quota")


@register(chain() + "SELECT image_id, region, site FROM sampled")
def density_sample(spark, sf_dir):
    return sampling.density_sample(captures(spark, sf_dir)).select("image_id", "region", "site")


@register(chain("event_type <> 'error'") + "SELECT image_id, region, quota FROM sampled")
def density_sample_filtered(spark, sf_dir):
    return sampling.density_sample(captures(spark, sf_dir, "event_type <> 'error'")).select("image_id", "region", "quota")


@register(chain() + f"SELECT image_id, region FROM pool JOIN quota USING (region) WHERE {hash01_sql(chr(39) + '42|s|' + chr(39) + ' || image_id')} < quota / n::DOUBLE")
def bernoulli_sample(spark, sf_dir):
    return sampling.density_sample(captures(spark, sf_dir), exact=False).select("image_id", "region")


@register(
    chain()
    + """, parts AS (SELECT d.region, d.area, d.n, count(s.image_id) AS sampled FROM density d JOIN sampled s USING (region) GROUP BY ALL)
SELECT coalesce(region, -1) AS region, floor(sum(area) * 100 + 0.5)::BIGINT AS area_hundredths, sum(n)::BIGINT AS available, sum(sampled)::BIGINT AS sampled FROM parts GROUP BY ROLLUP (region)"""
)
def sampling_table(spark, sf_dir):
    return sampling.sampling_table(captures(spark, sf_dir))


@register(
    """WITH d AS (SELECT n_nationkey, n_regionkey, 1 + n_nationkey % 5 AS area, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ALL),
q AS (SELECT *, least(n, floor((SELECT min(n / area::DOUBLE) FROM d) * area + 0.5)::BIGINT) AS quota FROM d)
SELECT coalesce(r_name, 'all') AS region_name, coalesce(n_nationkey, -1)::BIGINT AS nation, sum(n)::BIGINT AS n, sum(quota)::BIGINT AS quota
FROM q JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_nationkey)"""
)
def nation_density_rollup(spark, sf_dir):
    customers = load(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.count("*").alias("n"))
    nations = load(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey", (1 + F.col("n_nationkey") % 5).alias("area"))
    density = customers.join(nations, F.col("c_nationkey") == F.col("n_nationkey")).withColumn("density", F.col("n") / F.col("area")).withColumnRenamed("n_nationkey", "region")
    limits = sampling.quotas(density)
    names = nations.join(load(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    made = limits.join(names, F.col("region") == F.col("n_nationkey")).rollup("r_name", "region").agg(F.sum("n").alias("n"), F.sum("quota").alias("quota"))
    return made.select(F.coalesce("r_name", F.lit("all")).alias("region_name"), F.coalesce("region", F.lit(-1)).cast("long").alias("nation"), "n", "quota")


@register(chain() + "SELECT image_id, region, split FROM rows")
def stratified_split(spark, sf_dir):
    return split_rows(spark, sf_dir).select("image_id", "region", "split")


@register(
    chain()
    + """, s AS (SELECT region, count(*) AS size FROM sampled GROUP BY region),
c AS (SELECT region, floor(size * 0.7::DOUBLE) AS f0, floor(size * 0.85::DOUBLE) AS f1, size * 0.7::DOUBLE - floor(size * 0.7::DOUBLE) AS r0, size * 0.85::DOUBLE - floor(size * 0.85::DOUBLE) AS r1, sum(size) OVER () AS total FROM s),
k AS (SELECT region, f0 + (row_number() OVER (ORDER BY r0 DESC, region) <= floor(total * 0.7::DOUBLE + 0.5) - sum(f0) OVER ())::INT AS cut0, f1 + (row_number() OVER (ORDER BY r1 DESC, region) <= floor(total * 0.85::DOUBLE + 0.5) - sum(f1) OVER ())::INT AS cut1 FROM c)
SELECT region, CASE WHEN sr <= cut0 THEN 'train' WHEN sr <= cut1 THEN 'val' ELSE 'test' END AS split, count(*)::BIGINT AS n FROM ranked JOIN k USING (region) GROUP BY ALL"""
)
def stratified_split_reconciled(spark, sf_dir):
    rows = sampling.stratified_split(sampling.density_sample(captures(spark, sf_dir)), rounding="largest_remainder")
    return rows.groupBy("region", "split").agg(F.count("*").alias("n"))


@register(chain() + "SELECT split, count(*)::BIGINT AS n, count(DISTINCT site)::BIGINT AS sites FROM rows GROUP BY split")
def split_sizes(spark, sf_dir):
    return split_rows(spark, sf_dir).groupBy("split").agg(F.count("*").alias("n"), F.countDistinct("site").alias("sites"))


@register(chain() + "SELECT region, count(*)::BIGINT AS n, " + rounded_sql("count(*) / (SELECT count(*) FROM sampled)::DOUBLE") + " AS share FROM sampled GROUP BY region")
def class_balance(spark, sf_dir):
    from pyspark.sql import Window

    per = sampling.density_sample(captures(spark, sf_dir)).groupBy("region").agg(F.count("*").alias("n"))
    total = per.agg(F.sum("n").alias("total"))
    return per.crossJoin(total).select("region", "n", rounded(F.col("n") / F.col("total")).alias("share"))


@register(chain() + "SELECT 'train-test' AS pair, (SELECT count(*) FROM (SELECT image_id FROM rows WHERE split = 'train' INTERSECT SELECT image_id FROM rows WHERE split = 'test'))::BIGINT AS common, (SELECT count(*) FROM (SELECT image_id FROM sampled EXCEPT SELECT image_id FROM rows))::BIGINT AS lost")
def split_disjointness(spark, sf_dir):
    rows = split_rows(spark, sf_dir)
    side = lambda s: rows.where(F.col("split") == s).select("image_id")
    common = side("train").intersect(side("test")).agg(F.count("*").alias("common"))
    lost = sampling.density_sample(captures(spark, sf_dir)).select("image_id").exceptAll(rows.select("image_id")).agg(F.count("*").alias("lost"))
    return common.crossJoin(lost).select(F.lit("train-test").alias("pair"), "common", "lost")


_GROUP = hash01_sql("'42|g|' || site")


@register(chain() + f"SELECT image_id, CASE WHEN {_GROUP} < 0.7 THEN 'train' WHEN {_GROUP} < 0.85 THEN 'val' ELSE 'test' END AS split FROM sampled")
def grouped_split(spark, sf_dir):
    return sampling.grouped_split(sampling.density_sample(captures(spark, sf_dir)), "site").select("image_id", "split")


@register(chain() + "SELECT image_id, split FROM rows WHERE image_id NOT IN (SELECT image_id FROM near)")
def buffered_split(spark, sf_dir):
    return spatial.buffered_split(split_rows(spark, sf_dir)).select("image_id", "split")


@register(chain() + "SELECT image_id, region AS found FROM captures")
def assign_region(spark, sf_dir):
    return spatial.assign_region(captures(spark, sf_dir).select("image_id", "lat", "lon"), spatial.with_boxes(region_dim(spark))).select("image_id", "found")


@register(chain() + "SELECT region, count(*)::BIGINT AS n FROM rows WHERE split = 'test' AND site IN (SELECT site FROM train_sites) GROUP BY region")
def site_overlap(spark, sf_dir):
    return spatial.site_overlap(split_rows(spark, sf_dir)).groupBy("region").agg(F.count("*").alias("n"))


@register(chain() + "SELECT image_id FROM near")
def radius_overlap(spark, sf_dir):
    return spatial.near_training(split_rows(spark, sf_dir)).select("image_id")


@register(
    chain()
    + """SELECT count(*)::BIGINT AS n_test, count(*) FILTER (WHERE site IN (SELECT site FROM train_sites))::BIGINT AS same_site,
count(*) FILTER (WHERE image_id IN (SELECT image_id FROM near))::BIGINT AS within, count(*) FILTER (WHERE image_id NOT IN (SELECT image_id FROM near))::BIGINT AS beyond FROM rows WHERE split = 'test'"""
)
def overlap_audit(spark, sf_dir):
    return spatial.overlap_audit(split_rows(spark, sf_dir))


@register(
    chain()
    + """, t AS (SELECT site, list(DISTINCT heading) AS headings FROM rows WHERE split = 'train' GROUP BY site)
SELECT heading, count(*)::BIGINT AS n, count(*) FILTER (WHERE list_contains(headings, heading))::BIGINT AS same_heading, count(*) FILTER (WHERE NOT list_contains(headings, heading))::BIGINT AS other_heading
FROM rows JOIN t USING (site) WHERE split = 'test' GROUP BY heading"""
)
def heading_overlap(spark, sf_dir):
    return spatial.heading_overlap(split_rows(spark, sf_dir))


@register(chain() + f"SELECT region, {rounded_sql('c_lat')} AS c_lat, {rounded_sql('c_lon')} AS c_lon FROM centres")
def region_centroids(spark, sf_dir):
    return spatial.centroids(split_rows(spark, sf_dir)).select("region", rounded(F.col("c_lat")).alias("c_lat"), rounded(F.col("c_lon")).alias("c_lon"))


_CROSS = "(ex * ny - nx * ey)", "(nx * wy - wx * ny)"


@register(
    f"""WITH {CAPTURES_SQL}, o AS (SELECT region, min({{'a': lat, 'b': lon}}) AS s, max({{'a': lon, 'b': lat}}) AS e, max({{'a': lat, 'b': lon}}) AS n, min({{'a': lon, 'b': lat}}) AS w FROM captures GROUP BY region),
c AS (SELECT region, s.a AS lat0, s.b AS lon0, e.a - s.b AS ex, e.b - s.a AS ey, n.b - s.b AS nx, n.a - s.a AS ny, w.a - s.b AS wx, w.b - s.a AS wy FROM o)
SELECT region, {rounded_sql(f"lat0 + ((ey + ny) * {_CROSS[0]} + (ny + wy) * {_CROSS[1]}) / (3 * nullif({_CROSS[0]} + {_CROSS[1]}, 0))")} AS c_lat, {rounded_sql(f"lon0 + ((ex + nx) * {_CROSS[0]} + (nx + wx) * {_CROSS[1]}) / (3 * nullif({_CROSS[0]} + {_CROSS[1]}, 0))")} AS c_lon FROM c"""
)
def region_centroids_polygon(spark, sf_dir):
    """The centre of mass of the polygon that the outermost views of each region span."""
    made = spatial.polygon_centroids(spatial.outer_rings(captures(spark, sf_dir)))
    return made.select("region", rounded(F.col("c_lat")).alias("c_lat"), rounded(F.col("c_lon")).alias("c_lon"))


#: Reference predictors: right, always region 0, the next region, right or nothing.
RULES = {"right": ("region", "region"), "always_first": ("0", "0"), "next": ("pmod(region + 1, 8)", "(region + 1) % 8"), "every_other": ("CASE WHEN image_id % 2 = 0 THEN region END", "CASE WHEN image_id % 2 = 0 THEN region END")}


def _rules_sql(names: list[str]) -> str:
    preds = " UNION ALL ".join(f"SELECT '{n}' AS rule, *, {RULES[n][1]} AS pred FROM rows WHERE split = 'test'" for n in names)
    return chain() + f", p AS ({preds}) SELECT rule, count(*)::BIGINT AS n, count(*) FILTER (WHERE c.region IS NULL)::BIGINT AS unplaced, {rounded_sql('avg(CASE WHEN c.region IS NOT NULL THEN ' + haversine_sql('lat', 'lon', 'c_lat', 'c_lon') + ' END)', 4)} AS km FROM p LEFT JOIN centres c ON p.pred = c.region GROUP BY rule"


def _rules(spark, sf_dir, names):
    rows = split_rows(spark, sf_dir)
    options = F.array(*(F.struct(F.lit(n).alias("rule"), F.expr(RULES[n][0]).cast("int").alias("pred")) for n in names))
    test = rows.where("split = 'test'").select("lat", "lon", F.explode(options).alias("o")).select("lat", "lon", "o.rule", "o.pred")
    return spatial.centroid_error(test, spatial.centroids(rows), ["rule"]).select("rule", "n", "unplaced", rounded(F.col("km"), 4).alias("km"))


@register(_rules_sql(["right"]))
def centroid_error_floor(spark, sf_dir):
    return _rules(spark, sf_dir, ["right"])


@register(_rules_sql(list(RULES)))
def centroid_error_rules(spark, sf_dir):
    return _rules(spark, sf_dir, list(RULES))


@register(chain() + "SELECT image_id, lag(image_id) OVER (PARTITION BY site ORDER BY ts, image_id) AS previous_id FROM captures")
def nearest_capture(spark, sf_dir):
    return spatial.nearest_capture(captures(spark, sf_dir)).select("image_id", "previous_id")


@register(chain() + "SELECT image_id, region, CASE WHEN site IN (SELECT site FROM train_sites) THEN 'same site' WHEN image_id IN (SELECT image_id FROM near) THEN 'within' ELSE 'beyond' END AS stratum FROM rows WHERE split = 'test'")
def overlap_strata(spark, sf_dir):
    rows = split_rows(spark, sf_dir)
    same = spatial.site_overlap(rows).select("image_id", F.lit(True).alias("same"))
    near = spatial.near_training(rows).select("image_id", F.lit(True).alias("close"))
    kind = F.when(F.col("same"), "same site").when(F.col("close"), "within").otherwise("beyond")
    return rows.where("split = 'test'").join(same, "image_id", "left").join(near, "image_id", "left").select("image_id", "region", kind.alias("stratum"))


@register(chain() + "SELECT CASE WHEN region < 4 THEN 'west' ELSE 'east' END AS side, split, count(*)::BIGINT AS n FROM rows GROUP BY CUBE (CASE WHEN region < 4 THEN 'west' ELSE 'east' END, split)")
def split_cube(spark, sf_dir):
    return split_rows(spark, sf_dir).withColumn("side", F.when(F.col("region") < 4, "west").otherwise("east")).cube("side", "split").agg(F.count("*").alias("n"))


@register("SELECT event_type, count(*)::BIGINT AS n, sum((props::JSON->>'k')::BIGINT)::BIGINT AS k FROM events GROUP BY event_type")
def json_props(spark, sf_dir):
    return load(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.from_json("props", "k long")["k"]).alias("k"))


@register(
    """WITH g AS (SELECT user_id, ts, (lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL OR ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE)::INT AS fresh FROM events),
s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM g)
SELECT user_id, count(DISTINCT session)::BIGINT AS sessions, count(*)::BIGINT AS n FROM s GROUP BY user_id"""
)
def session_captures(spark, sf_dir):
    rows = load(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    cut = rows.groupBy("user_id", F.session_window("ts", "30 minutes")).agg(F.count("*").alias("n"))
    return cut.groupBy("user_id").agg(F.count("*").alias("sessions"), F.sum("n").alias("n"))


@register(
    """WITH d AS (SELECT doc_id, md5(text) AS h, ('0x' || substr(md5('42|d|' || doc_id), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u FROM documents), s AS (SELECT *, CASE WHEN u < 0.7 THEN 'train' WHEN u < 0.85 THEN 'val' ELSE 'test' END AS split FROM d)
SELECT count(*)::BIGINT AS n_test, count(*) FILTER (WHERE h IN (SELECT h FROM s WHERE split = 'train'))::BIGINT AS same_text FROM s WHERE split = 'test'"""
)
def content_overlap(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("h"), seeded(42, "d", F.col("doc_id")).alias("u"))
    rows = docs.withColumn("split", F.when(F.col("u") < 0.7, "train").when(F.col("u") < 0.85, "val").otherwise("test"))
    train = rows.where("split = 'train'").select("h", F.lit(1).alias("seen")).distinct()
    return rows.where("split = 'test'").join(train, "h", "left").agg(F.count("*").alias("n_test"), F.count("seen").alias("same_text"))


_TEXT_GROUP = hash01_sql("'42|g|' || md5(text)")


@register(f"SELECT doc_id, CASE WHEN {_TEXT_GROUP} < 0.7 THEN 'train' WHEN {_TEXT_GROUP} < 0.85 THEN 'val' ELSE 'test' END AS split FROM documents")
def content_grouped_split(spark, sf_dir):
    docs = load(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("text_hash"))
    return sampling.grouped_split(docs, "text_hash").select("doc_id", "split")


@register("SELECT item_id, count(*)::BIGINT AS n FROM benchmark b JOIN documents d ON contains(d.text, b.text) GROUP BY item_id")
def contamination_lookup(spark, sf_dir):
    """Which benchmark passages documents contain literally."""
    docs = load(spark, sf_dir, "documents").select(F.col("doc_id").alias("doc"), "text")
    return duplicates.containing(docs, load(spark, sf_dir, "benchmark").select(F.col("item_id").alias("item"), F.col("text").alias("passage"))).groupBy(F.col("item").alias("item_id")).agg(F.count("*").alias("n"))


@register(chain() + f""", places AS (SELECT lat, lon, min(image_id) AS id FROM rows GROUP BY lat, lon)
SELECT p.id AS a, q.id AS b, {rounded_sql(haversine_sql('p.lat', 'p.lon', 'q.lat', 'q.lon'), 4)} AS distance FROM places p JOIN places q ON p.id < q.id AND abs(p.lat - q.lat) < 0.01 AND abs(p.lon - q.lon) < 0.01 WHERE {haversine_sql('p.lat', 'p.lon', 'q.lat', 'q.lon')} <= 0.1""")
def near_duplicate_places(spark, sf_dir):
    """Different positions of sampled views within 100 m: the duplicates that a geographic filter would look at."""
    made = duplicates.near_duplicates(split_rows(spark, sf_dir), "geo", "image_id", 0.1)
    return made.select("a", "b", rounded(F.col("distance"), 4).alias("distance"))


_MOVED = "CASE WHEN image_id % 29 = 0 THEN lat + 10 ELSE lat END"


@register(chain() + "SELECT region, count(*)::BIGINT AS n FROM captures WHERE image_id % 29 <> 0 GROUP BY region")
def polygon_filter(spark, sf_dir):
    """Captures inside the regions' polygons, before any sampling; every 29th one is moved far away to be filtered out."""
    moved = captures(spark, sf_dir).withColumn("lat", F.expr(_MOVED))
    return spatial.eligible_points(moved.select("image_id", "region", "lat", "lon"), spatial.with_boxes(region_dim(spark))).groupBy("region").agg(F.count("*").alias("n"))


_WORD_SET = r"list_distinct(list_filter(string_split_regex(lower(coalesce(text, '')), '\s+'), lambda w: w <> ''))"


@register(
    f"""WITH d AS (SELECT doc_id, md5(text) AS h, {_WORD_SET} AS w, ('0x' || substr(md5('42|d|' || doc_id), 1, 8))::BIGINT / 4294967296.0::DOUBLE AS u FROM documents WHERE text IS NOT NULL), s AS (SELECT *, CASE WHEN u < 0.7 THEN 'train' WHEN u < 0.85 THEN 'val' ELSE 'test' END AS split FROM d),
k AS (SELECT h, any_value(w) AS w FROM s GROUP BY h), x AS (SELECT h, unnest(w) AS word FROM k), p AS (SELECT a.h AS a, b.h AS b, count(*) AS c FROM x a JOIN x b ON a.word = b.word AND a.h <> b.h GROUP BY 1, 2),
near AS (SELECT a, b FROM p JOIN k x ON p.a = x.h JOIN k y ON p.b = y.h WHERE c / (len(x.w) + len(y.w) - c)::DOUBLE > 0.8), train AS (SELECT DISTINCT h FROM s WHERE split = 'train'),
hit AS (SELECT DISTINCT a FROM near JOIN train ON b = h)
SELECT count(*)::BIGINT AS n_test, count(*) FILTER (WHERE h IN (SELECT h FROM train))::BIGINT AS same_text, count(*) FILTER (WHERE h IN (SELECT h FROM train) OR h IN (SELECT a FROM hit))::BIGINT AS same_or_near FROM s WHERE split = 'test'"""
)
def content_overlap_near(spark, sf_dir):
    """Test documents whose text, or a near copy of it (word sets with a similarity over 0.8), is in training."""
    u = seeded(42, "d", F.col("doc_id"))
    docs = load(spark, sf_dir, "documents").where("text is not null").select("doc_id", "text", F.md5("text").alias("h"), F.when(u < 0.7, "train").when(u < 0.85, "val").otherwise("test").alias("split"))
    sides = checkpointed(docs.groupBy("h").agg(F.min("doc_id").alias("rep"), F.max((F.col("split") == "train").cast("int")).alias("trained")))
    pairs = checkpointed(duplicates.near_duplicates(duplicates.representatives(docs.select("doc_id", "text"), "doc_id", "text"), "text", "doc_id", 0.2).select("a", "b"))
    both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
    near = both.join(sides.where("trained = 1").select(F.col("rep").alias("b")), "b").select(F.col("a").alias("rep"), F.lit(1).alias("near")).distinct()
    told = sides.join(near, "rep", "left").select(F.col("h").alias("hash"), "trained", "near")
    test = docs.where("split = 'test'").join(told, F.col("h") == F.col("hash"))
    return test.agg(F.count("*").alias("n_test"), F.count_if(F.col("trained") == 1).alias("same_text"), F.count_if((F.col("trained") == 1) | F.col("near").isNotNull()).alias("same_or_near"))
