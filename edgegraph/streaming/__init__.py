"""Streams of events as streams of edges, each checked against its batch twin."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans import Scratch

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


def _source(spark: SparkSession, d: str, files: int = 4, late: DataFrame | None = None) -> tuple[DataFrame, Scratch]:
    """events as a stream of several files that arrive in the order of time, ts in session time (UTC).

    late: rows that arrive in one more file after all others. The last two files hold a mark of the end: a row
    without event_id, far ahead in time, which lets the watermark pass the last real row; queries with a
    watermark leave it out behind the watermark, the others see no need of it and do so at once.
    """
    scratch = Scratch(spark, "stream")
    e = spark.read.parquet(f"{d}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    at = F.unix_micros("ts")
    cuts = e.agg(F.percentile_approx(at, F.array(*(F.lit(i / files) for i in range(1, files))))).first()[0] or []
    edges = [None, *cuts, None]
    for low, high in zip(edges, edges[1:]):
        part = e.where(F.lit(True) if low is None else at >= low).where(F.lit(True) if high is None else at < high)
        part.coalesce(1).write.mode("append").parquet(f"{scratch.path}/in")
    if late is not None:
        late.select(e.columns).coalesce(1).write.mode("append").parquet(f"{scratch.path}/in")
    end = e.agg((F.max("ts") + F.expr("interval 1000 days")).alias("ts")).select(F.lit(None).cast(e.schema["event_id"].dataType).alias("event_id"), "ts", F.lit(None).cast(e.schema["user_id"].dataType).alias("user_id"), F.lit(None).cast("string").alias("event_type"))
    for _ in range(2):  # the watermark that the first one sets is in force from the second one on
        end.coalesce(1).write.mode("append").parquet(f"{scratch.path}/in")
    return spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(f"{scratch.path}/in"), scratch


def _marked(s: DataFrame, delay: str) -> DataFrame:
    """The rows of a stream with a watermark, without the mark of the end."""
    # the condition looks at ts too, or it would be moved below the watermark, which would not see the mark
    return s.withWatermark("ts", delay).where(F.when(F.col("ts").isNotNull(), F.col("event_id").isNotNull()))


def _span(spark: SparkSession, d: str) -> int:
    """Seconds from the first event to the last, rounded up."""
    ts = F.col("ts").cast("timestamp")
    first, last = spark.read.parquet(f"{d}/events.parquet").agg(F.unix_seconds(F.min(ts)), F.unix_seconds(F.max(ts))).first()
    return 1 if first is None else last - first + 1


def _drain(stream: DataFrame, scratch: Scratch, mode: str = "append", each=None, whole=None) -> DataFrame:
    """All that a stream yields, through a file sink (or each(batch, id, folder)) until its source is exhausted;
    whole reads what each wrote, if that is not one table."""
    spark, out = stream.sparkSession, f"{scratch.path}/out-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{out}-state").trigger(availableNow=True)
    if each is not None:
        q = writer.outputMode(mode).foreachBatch(lambda b, i: each(b, i, out)).start()
    else:
        q = writer.outputMode(mode).format("parquet").option("path", out).start()
    q.awaitTermination()
    if each is None:
        return spark.read.schema(stream.schema).parquet(out)
    return spark.read.parquet(out) if whole is None else whole(out)


@query("select time_bucket(interval 1 day, ts) as start, event_type, count(*) n from events group by all")
def op_stream_tumbling(spark, d):
    s, scratch = _source(spark, d)
    rows = _marked(s, "1 day").groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", "n")
    return _drain(rows, scratch)


@query("select s as start, count(*) n from (select unnest([time_bucket(interval 12 hour, ts), time_bucket(interval 12 hour, ts) - interval 12 hour]) s from events) group by all")
def op_stream_sliding(spark, d):
    s, scratch = _source(spark, d)
    rows = _marked(s, "1 day").groupBy(F.window("ts", "1 day", "12 hours")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")
    return _drain(rows, scratch)


@query("select user_id, min(ts) as start, count(*) n from (select *, sum(new) over (partition by user_id order by ts, event_id) g from (select *, case when ts - lag(ts) over (partition by user_id order by ts, event_id) < interval 6 hour then 0 else 1 end new from events)) group by user_id, g")
def op_stream_session(spark, d):
    s, scratch = _source(spark, d)
    rows = _marked(s, "1 day").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")
    return _drain(rows, scratch)


@query("select distinct user_id, event_type from events")
def op_stream_dedupe(spark, d):
    s, scratch = _source(spark, d)
    rows = s.where("event_id is not null").select("user_id", "event_type").dropDuplicates()  # no bound: its state is the result
    return _drain(rows, scratch)


@query("select c.event_id click, p.event_id purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour")
def op_stream_join(spark, d):
    s, scratch = _source(spark, d)
    delay = f"{_span(spark, d)} seconds"  # no row is further behind, in whatever order files arrive
    c = s.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")).withWatermark("ct", delay)
    p = s.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pt")).withWatermark("pt", delay)
    rows = c.join(p, F.expr("cu = pu and pt >= ct and pt <= ct + interval 1 hour")).select("click", "purchase")
    return _drain(rows, scratch)


def assign_arriving(batch: DataFrame, placed: DataFrame | None, k: int) -> DataFrame:
    """(src, dst, part) for the edges of a batch: a part that holds both ends, else one end (the smallest
    number), else the smallest parts: such edges fill the parts up to one level, dealt by hash in proportion
    to what each lacks. placed: earlier (src, dst, part)."""
    batch = batch.select("src", "dst").distinct()
    sizes = [0] * k
    if placed is None:
        homeless = batch.withColumn("home", F.lit(None).cast("int"))
    else:
        batch = batch.join(placed.select("src", "dst"), ["src", "dst"], "left_anti")
        homes = placed.select(F.explode(F.array("src", "dst")).alias("vid"), "part").distinct()
        ends = batch.select("src", "dst", F.explode(F.array("src", "dst")).alias("vid")).join(homes, "vid")
        best = ends.groupBy("src", "dst", "part").agg(F.count(F.lit(1)).alias("n")).groupBy("src", "dst").agg(F.max_by("part", F.struct("n", -F.col("part"))).alias("home"))
        homeless = batch.join(best, ["src", "dst"], "left")
        for r in placed.groupBy("part").count().collect():  # k rows
            sizes[r["part"]] += r["count"]
    found = {r["home"]: r["count"] for r in homeless.groupBy("home").count().collect()}  # k + 1 rows at most
    sizes = [n + found.get(i, 0) for i, n in enumerate(sizes)]
    shares = fill_level(sizes, found.get(None, 0))
    place = F.pmod(F.xxhash64("src", "dst"), F.lit(max(1, sum(shares))))
    dealt = F.lit(k - 1)
    for i in reversed(range(k)):
        dealt = F.when(place < sum(shares[: i + 1]), i).otherwise(dealt)
    return homeless.select("src", "dst", F.coalesce("home", dealt).cast("int").alias("part"))


def fill_level(sizes: list[int], n: int) -> list[int]:
    """How many of n further items each part gets, so that the smallest rise to one level."""
    order, out = sorted(range(len(sizes)), key=lambda i: (sizes[i], i)), [0] * len(sizes)
    for used in range(len(order), 0, -1):
        level, rest = divmod(n + sum(sizes[i] for i in order[:used]), used)
        if level >= sizes[order[used - 1]]:
            for j, i in enumerate(order[:used]):
                out[i] = level + (j < rest) - sizes[i]
            break
    return out


@query("select count(*) n_edges, 0::bigint twice, 0::bigint outside from (select distinct user_id * 16 + 2 a, hash_type b from (select user_id, event_type hash_type from events))")
def op_stream_assign(spark, d):
    s, scratch = _source(spark, d)
    edges = s.where("event_id is not null").select((F.col("user_id") * 16 + 2).alias("src"), (F.crc32(F.col("event_type").cast("binary")) * 16 + 6).alias("dst"))

    def each(batch: DataFrame, i: int, out: str) -> None:
        session = batch.sparkSession
        placed = session.read.schema("src long, dst long, part int").parquet(out) if i else None
        assign_arriving(batch, placed, 8).write.mode("append").parquet(out)

    got = _drain(edges, scratch, "append", each)
    per = got.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"), F.max("part").alias("p"), F.min("part").alias("q"))
    return per.agg(F.count(F.lit(1)).alias("n_edges"), F.count(F.when(F.col("n") > 1, 1)).alias("twice"), F.count(F.when((F.col("p") > 7) | (F.col("q") < 0), 1)).alias("outside"))


def current_labels(vids: DataFrame, parents: DataFrame | None, most_rounds: int = 64) -> DataFrame:
    """(vid, comp) for vids (vid): up the chain of parents (label, parent), to labels that have none; a
    vertex nobody has merged yet is its own label."""
    now = vids.select("vid", F.col("vid").alias("comp"))
    if parents is None:
        return now
    scratch = Scratch(vids.sparkSession, "labels")
    for _ in range(most_rounds):
        up = now.join(parents.select(F.col("label").alias("comp"), "parent"), "comp", "left")
        now = scratch.store(up.select("vid", F.coalesce("parent", "comp").alias("comp"), F.col("parent").isNotNull().alias("moved")), "now")
        if not now.where("moved").limit(1).count():
            return now.select("vid", "comp")
        now = now.select("vid", "comp")
    raise RuntimeError("chains of labels did not end")


def merge_arriving(batch: DataFrame, parents: DataFrame | None) -> DataFrame:
    """(label, parent) for the labels that the links (a, b) of a batch merge into smaller ones. Only the
    labels of vertices that the batch touches are read and only they are merged."""
    from ..model import EdgeGraph
    from ..operators.baselines import vertex_rounds_components

    scratch = Scratch(batch.sparkSession, "merge")
    links = scratch.store(batch.select("a", "b").distinct())
    labels = scratch.store(current_labels(links.select(F.explode(F.array("a", "b")).alias("vid")).distinct(), parents))
    side = lambda c: labels.select(F.col("vid").alias(c), F.col("comp").alias(f"l{c}"))
    between = links.join(side("a"), "a").join(side("b"), "b").where("la != lb")
    merged = vertex_rounds_components(EdgeGraph.from_pairs(between, "la", "lb"))[0]
    return merged.where("vid != comp").select(F.col("vid").alias("label"), F.col("comp").alias("parent"))


_LINKS = "e as (select distinct user_id * 16 + 2 as src, ((user_id * 7 + length(event_type)) % 11 + 1000000) * 16 + 6 as dst from events where event_id % 2 = user_id % 2 and user_id % 3 <> 0), h as (select src a, dst b from e union all select dst, src from e)"


@query(f"with recursive {_LINKS}, t(vid, c) using key (vid) as (select vid, vid c from (select distinct a vid from h) union select vid, min(c) c from (select h.b vid, t.c from t join h on h.a = t.vid join recurring.t r on r.vid = h.b where t.c < r.c) group by vid) select (vid - 2) // 16 user_id, (c - 2) // 16 comp from t where vid % 16 = 2")
def op_stream_components(spark, d):
    """Labels of users linked through groups of their events, kept up to date batch by batch: merges of
    labels are appended, and only labels that a batch touches are looked up."""
    s, scratch = _source(spark, d, files=2)
    some = s.where("event_id is not null and event_id % 2 = user_id % 2 and user_id % 3 <> 0")
    edges = some.select((F.col("user_id") * 16 + 2).alias("a"), (((F.col("user_id") * 7 + F.length("event_type")) % 11 + 1_000_000) * 16 + 6).alias("b"))

    def each(batch: DataFrame, i: int, out: str) -> None:
        session = batch.sparkSession
        parents = session.read.schema("label long, parent long").parquet(f"{out}/parents") if i else None
        batch.select("a").distinct().write.mode("append").parquet(f"{out}/users")
        merge_arriving(batch, parents).write.mode("append").parquet(f"{out}/parents")

    def whole(out: str) -> DataFrame:
        users = spark.read.schema("a long").parquet(f"{out}/users").select(F.col("a").alias("vid")).distinct()
        return current_labels(users, spark.read.schema("label long, parent long").parquet(f"{out}/parents"))

    found = _drain(edges, scratch, "append", each, whole)
    return found.select(F.shiftright("vid", 4).alias("user_id"), F.shiftright("comp", 4).alias("comp"))


@query("select time_bucket(interval 1 day, ts) as start, count(*) n from events group by all")
def op_stream_late(spark, d):
    """Rows far behind the watermark are left out of windows: a file that repeats the first days' events
    after all others adds none, and every window still comes once."""
    e = spark.read.parquet(f"{d}/events.parquet").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    old = e.where(F.col("ts") < e.agg((F.min("ts") + F.expr("interval 3 days")).alias("t")).first()["t"])
    s, scratch = _source(spark, d, late=old)
    rows = _marked(s, "1 day").groupBy(F.window("ts", "1 day")).agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("start"), "n")
    return _drain(rows, scratch)
