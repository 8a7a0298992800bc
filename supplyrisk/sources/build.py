"""Orders and their lines as a build history.

Each order is a build step that releases part (order key mod number of parts); its lines
are what the step used, in the newest release of that part before the order.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from supplyrisk.operators.graph import BuildHistory
from supplyrisk.operators.windows import last_before
from supplyrisk.plans.memo import memo
from supplyrisk.plans.staging import Staged
from supplyrisk.sources.schema import BASE, BUILDER, COPY, ENV, HOST_BITS, KEY_BITS, RELEASE, STEP, STORAGE, code_of, copied_artifact, copy_host, key_of, pack, pack_copy
from supplyrisk.sources.tables import table


def _month(date: Column) -> Column:
    return F.year(date) * 12 + F.month(date) - 1 - 1970 * 12


def env_key(customer: Column, date: Column) -> Column:
    return customer.cast("long") * 1200 + _month(date)


def used_releases(lines: DataFrame, releases: DataFrame, at_most: DataFrame | None = None) -> DataFrame:
    """As-of join: each line (part_key, at, order_key and more) with the newest release of
    its part strictly before it; used_order_key is null if there is none.

    One window per part over lines and releases together, so every row is moved once; a very
    popular part's rows are cut by time (operators/windows.py)."""
    extra = [c for c in lines.columns if c not in ("part_key", "at", "order_key")]
    null = [F.lit(None).cast(lines.schema[c].dataType).alias(c) for c in extra]
    both = lines.select("part_key", "at", "order_key", *extra, F.lit(0).alias("is_release")).unionAll(releases.select("part_key", "at", "order_key", *null, F.lit(1).alias("is_release")))
    # At one place in time lines come first: a release is not used by its own build.
    newest = F.when(F.col("is_release") == 1, F.col("order_key"))
    return last_before(both, "part_key", ["at", "order_key", "is_release"], newest, "used_order_key", at_most=at_most).where("is_release = 0").drop("is_release")


def lines_and_releases(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Distinct lines with their order's customer and date; releases; orders."""
    n_parts = table(spark, sf_dir, "part").count()  # of file footers only
    orders = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("order_key"), F.col("o_custkey").alias("cust_key"), F.col("o_orderdate").alias("at"))
    raw = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("order_key"), F.col("l_partkey").alias("part_key"), F.col("l_suppkey").alias("supp_key"), F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("state"))
    lines = raw.distinct().join(orders, "order_key")
    releases = orders.select((F.col("order_key") % n_parts).alias("part_key"), "at", "order_key")
    return lines, releases, orders


def asof_lines(spark: SparkSession, sf_dir: str, suppliers: DataFrame | None = None) -> DataFrame:
    """suppliers: supp_key of those whose lines are wanted, a few; None: all."""
    lines, releases, _ = lines_and_releases(spark, sf_dir)
    if suppliers is not None:
        lines = lines.join(suppliers, "supp_key", "left_semi")
    # Lines that name no order are counted too, so this is no less than what a part has.
    named = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("part_key")).unionAll(releases.select("part_key"))
    return used_releases(lines, releases, named.groupBy("part_key").agg(F.count("*").alias("n")))


def copy_bits(spark: SparkSession, sf_dir: str) -> int | None:
    """Width of a host key in the ids of copies; None if artifact and host keys do not fit
    together, so that copies have to be numbered."""

    def bits(name: str, column: str) -> int:
        return int(table(spark, sf_dir, name).agg(F.coalesce(F.max(column), F.lit(0))).first()[0]).bit_length()

    def make() -> int | None:
        host = max(HOST_BITS, bits("supplier", "s_suppkey"))
        return host if max(bits("orders", "o_orderkey"), bits("part", "p_partkey")) <= KEY_BITS - 1 - host else None

    return memo(spark, sf_dir, "copy-bits", make)


def numbered_copies(spark: SparkSession, sf_dir: str, used: DataFrame) -> DataFrame:
    """up, supp_key, copy: a number for each fetched copy, kept in the shared folder."""
    pairs = used.select("up", "supp_key").distinct()
    number = F.lit(COPY << KEY_BITS).cast("long").bitwiseOR(F.monotonically_increasing_id())
    return memo(spark, sf_dir, "copy-numbers", lambda: Staged(pairs.withColumn("copy", number), "copy-numbers").df)


def with_copy(spark: SparkSession, sf_dir: str, used: DataFrame) -> DataFrame:
    """used (up, supp_key and more) with `copy`, the vertex fetched from that storage host."""
    host_bits = copy_bits(spark, sf_dir)
    if host_bits is not None:
        return used.withColumn("copy", pack_copy(F.col("up"), F.col("supp_key"), host_bits))
    return used.join(numbered_copies(spark, sf_dir, used.where(~((F.col("flag") == "A") & (F.col("state") == "O")))), ["up", "supp_key"], "left")


def copy_parts(spark: SparkSession, sf_dir: str, copies: DataFrame, col: str = "vid") -> DataFrame:
    """copies with `up` (the copied artifact's id) and `supp_key` of each."""
    host_bits = copy_bits(spark, sf_dir)
    if host_bits is not None:
        return copies.withColumns({"up": copied_artifact(F.col(col), host_bits), "supp_key": copy_host(F.col(col), host_bits)})
    numbers = memo(spark, sf_dir, "copy-numbers", lambda: None)
    if numbers is None:
        raise ValueError("copies are numbered when the graph is built")
    return copies.join(numbers.withColumnRenamed("copy", col), col)


def home(spark: SparkSession, sf_dir: str) -> Callable[[Column], Column]:
    """What a vertex id is dealt to blocks by: a step stays with its release, a copy with what was
    copied, an environment with its host, so only what a step uses crosses blocks."""
    host_bits = copy_bits(spark, sf_dir)

    def of(vid: Column) -> Column:
        code, key = code_of(vid), key_of(vid)
        at = F.when(code == STEP, F.lit(RELEASE << KEY_BITS).cast("long").bitwiseOR(key)).when(code == ENV, F.lit(BUILDER << KEY_BITS).cast("long").bitwiseOR(F.floor(key / 1200)))
        if host_bits is not None:
            at = at.when(code == COPY, copied_artifact(vid, host_bits))
        return at.otherwise(vid)

    return of


def graph(spark: SparkSession, sf_dir: str, cyclic: bool = False) -> BuildHistory:
    """cyclic: the build host holds the newest release, not the base artifact."""
    _, _, orders = lines_and_releases(spark, sf_dir)
    used = asof_lines(spark, sf_dir)
    base = pack(BASE, F.col("part_key"))
    up = F.when(F.col("used_order_key").isNull(), base).otherwise(pack(RELEASE, F.col("used_order_key")))
    on_host = (F.col("flag") == "A") & (F.col("state") == "O")
    used = used.withColumns({"up": up, "on_host": on_host})
    used = with_copy(spark, sf_dir, used)
    step, env = pack(STEP, F.col("order_key")), pack(ENV, env_key(F.col("cust_key"), F.col("at")))
    host, storage = pack(BUILDER, F.col("cust_key")), pack(STORAGE, F.col("supp_key"))

    fetched = used.where(~F.col("on_host"))
    copies = fetched.select("up", "copy", storage.alias("storage")).distinct()
    role = F.when(F.col("flag") == "N", "feeds").when(F.col("flag") == "R", "tools").otherwise("present_in")
    uses = fetched.select(F.col("copy").alias("src"), F.when(F.col("flag") == "A", env).otherwise(step).alias("dst"), role.alias("label"))
    held = used.where("on_host").select((F.col("up") if cyclic else base).alias("src"), host.alias("dst"), F.lit("present_in").alias("label"))
    envs = orders.select(host.alias("host"), env.alias("env")).distinct()
    pieces = [
        uses.unionAll(held).distinct(),
        copies.select(F.col("up").alias("src"), F.col("storage").alias("dst"), F.lit("published_to").alias("label")),
        copies.select(F.col("storage").alias("src"), F.col("copy").alias("dst"), F.lit("fetched_from").alias("label")),
        envs.select(F.col("host").alias("src"), F.col("env").alias("dst"), F.lit("hosts_env").alias("label")),
        orders.select(env.alias("src"), step.alias("dst"), F.lit("runs_step").alias("label")),
        orders.select(step.alias("src"), pack(RELEASE, F.col("order_key")).alias("dst"), F.lit("produces").alias("label")),
    ]
    edges = pieces[0]
    for p in pieces[1:]:
        edges = edges.unionAll(p)
    no_props = F.lit(None).cast("map<string,string>").alias("props")
    # Edge ids are negative, vertex ids positive: the two never meet.
    eid = (-1 - F.xxhash64("src", "dst", "label").bitwiseAND(F.lit(2**62 - 1))).alias("eid")
    edges = edges.select(eid, "src", "dst", "label", no_props)

    def of(df: DataFrame, vid: Column, kind: str, akey: Column | None = None) -> DataFrame:
        return df.select(vid.alias("vid"), F.lit(kind).alias("vtype"), (akey if akey is not None else F.lit(None).cast("string")).alias("akey"), no_props)

    def name(artifact: Column) -> Column:
        return F.concat(F.when(F.shiftrightunsigned(artifact, 59) == BASE, "P").otherwise("R"), key_of(artifact).cast("string"))

    part, supplier, customer = (table(spark, sf_dir, t) for t in ("part", "supplier", "customer"))
    vertices = (
        of(part, pack(BASE, F.col("p_partkey")), "artifact", F.concat(F.lit("P"), F.col("p_partkey").cast("string")))
        .unionAll(of(orders, pack(RELEASE, F.col("order_key")), "artifact", F.concat(F.lit("R"), F.col("order_key").cast("string"))))
        .unionAll(of(copies, F.col("copy"), "artifact", name(F.col("up"))))
        .unionAll(of(orders, step, "step"))
        .unionAll(of(envs, F.col("env"), "env"))
        .unionAll(of(supplier, pack(STORAGE, F.col("s_suppkey")), "host"))
        .unionAll(of(customer, pack(BUILDER, F.col("c_custkey")), "host"))
    )
    return BuildHistory(vertices, edges)


def is_whole(spark: SparkSession, sf_dir: str) -> bool:
    """Whether every part, supplier and customer that lines and orders name is there, and no key is null."""
    for child, column, parent, key in (("lineitem", "l_partkey", "part", "p_partkey"), ("lineitem", "l_suppkey", "supplier", "s_suppkey"), ("orders", "o_custkey", "customer", "c_custkey")):
        named = table(spark, sf_dir, child).select(F.col(column).alias("key")).distinct()
        if named.join(table(spark, sf_dir, parent).select(F.col(key).alias("key")), "key", "left_anti").limit(1).count():
            return False
    return not table(spark, sf_dir, "orders").where("o_orderkey is null or o_orderdate is null").limit(1).count()


def folded(spark: SparkSession, sf_dir: str, cyclic: bool = False) -> DataFrame:
    """src, dst, label: the edges that compiling graph() gives where is_whole(). All of a copy's rows follow from lines
    of one part, so they are made where the as-of join leaves them and moved no more."""
    _, _, orders = lines_and_releases(spark, sf_dir)
    used = asof_lines(spark, sf_dir)
    base = pack(BASE, F.col("part_key"))
    up = F.when(F.col("used_order_key").isNull(), base).otherwise(pack(RELEASE, F.col("used_order_key")))
    used = with_copy(spark, sf_dir, used.withColumns({"up": up, "on_host": (F.col("flag") == "A") & (F.col("state") == "O")}))
    step, env = pack(STEP, F.col("order_key")), pack(ENV, env_key(F.col("cust_key"), F.col("at")))
    edge = lambda src, dst, label: F.struct(src.alias("src"), dst.alias("dst"), label.alias("label"))
    role = F.when(F.col("flag") == "N", F.lit("feeds")).when(F.col("flag") == "R", F.lit("tools")).otherwise(F.lit("present_in"))
    use = edge(F.col("copy"), F.when(F.col("flag") == "A", env).otherwise(step), role)
    fetched = F.array(use, edge(pack(STORAGE, F.col("supp_key")), F.col("copy"), F.lit("fetched_from")), edge(F.col("up"), F.col("copy"), F.lit("copy")))
    held = F.array(edge(F.col("up") if cyclic else base, pack(BUILDER, F.col("cust_key")), F.lit("present_in")))
    lines = used.select("part_key", F.inline(F.when(F.col("on_host"), held).otherwise(fetched))).distinct()
    host = pack(BUILDER, F.col("cust_key"))
    envs = orders.select(host.alias("src"), env.alias("dst"), F.lit("hosts_env").alias("label"))
    built = orders.select(F.inline(F.array(edge(env, step, F.lit("runs_step")), edge(step, pack(RELEASE, F.col("order_key")), F.lit("produces")))))
    return lines.select("src", "dst", "label").unionAll(envs.distinct()).unionAll(built.distinct())


def vertices_of(spark: SparkSession, sf_dir: str, prop: DataFrame) -> tuple[DataFrame, DataFrame]:
    """vid, vtype of all vertices of graph(), and of those that may have no out-edge. prop: its compiled edges."""
    part, supplier, customer, orders = (table(spark, sf_dir, t) for t in ("part", "supplier", "customer", "orders"))
    of = lambda df, vid, kind: df.select(vid.alias("vid"), F.lit(kind).alias("vtype"))
    ends = of(part, pack(BASE, F.col("p_partkey")), "artifact").unionAll(of(orders, pack(RELEASE, F.col("o_orderkey")), "artifact"))
    ends = ends.unionAll(of(supplier, pack(STORAGE, F.col("s_suppkey")), "host")).unionAll(of(customer, pack(BUILDER, F.col("c_custkey")), "host"))
    inner = of(prop.where("label = 'fetched_from'"), F.col("dst"), "artifact").unionAll(of(orders, pack(STEP, F.col("o_orderkey")), "step"))
    return ends.unionAll(inner).unionAll(of(prop.where("label = 'hosts_env'"), F.col("dst"), "env")), ends


def copy_sides(spark: SparkSession, sf_dir: str, prop: DataFrame) -> DataFrame:
    """host, akey, vid, side of copies and of what they were copied from, from compiled edges."""
    name = F.concat(F.when(code_of(F.col("src")) == BASE, "P").otherwise("R"), key_of(F.col("src")).cast("string"))
    host = prop.where("label = 'fetched_from'").select(F.col("src").alias("host"), F.col("dst").alias("copy"))
    met = prop.where("label = 'copy'").select(F.col("dst").alias("copy"), F.col("src").alias("up"), name.alias("akey")).join(host, "copy")
    both = met.select("host", "akey", F.col("copy").alias("vid"), F.lit("fetched").alias("side")).unionAll(met.select("host", "akey", F.col("up").alias("vid"), F.lit("held").alias("side")))
    on_host = prop.where("label = 'present_in'").where(code_of(F.col("dst")) == BUILDER).select(F.col("dst").alias("host"), name.alias("akey"), F.col("src").alias("vid"), F.lit("held").alias("side"))
    return both.unionAll(on_host)


def seeds(spark: SparkSession, sf_dir: str, kinds: str = "SV,SM") -> DataFrame:
    """vid, kind. SV: large parts; SM: a few parts; HM: a few suppliers; HV: customers in debt."""
    part, supplier, customer = (table(spark, sf_dir, t) for t in ("part", "supplier", "customer"))
    all_kinds = {
        "SV": part.where("p_size >= 45").select(pack(BASE, F.col("p_partkey")).alias("vid"), F.lit("SV").alias("kind")),
        "SM": part.where("p_partkey % 997 = 5").select(pack(BASE, F.col("p_partkey")).alias("vid"), F.lit("SM").alias("kind")),
        "HM": supplier.where("s_suppkey % 97 = 3").select(pack(STORAGE, F.col("s_suppkey")).alias("vid"), F.lit("HM").alias("kind")),
        "HV": customer.where("c_acctbal < -800").select(pack(BUILDER, F.col("c_custkey")).alias("vid"), F.lit("HV").alias("kind")),
    }
    out = None
    for k in filter(None, kinds.split(",")):
        out = all_kinds[k] if out is None else out.unionAll(all_kinds[k])
    return out if out is not None else all_kinds["SV"].limit(0)


def vertex_name(vid: Column, host_bits: int = HOST_BITS) -> Column:
    """What a person would call a vertex: P12 part, R5 release, CP12@3 copy, T5 step,
    B7/1995-01 environment, HS3 storage host, HC7 build host."""

    def artifact(x: Column) -> Column:
        return F.concat(F.when(code_of(x) == BASE, "P").otherwise("R"), key_of(x).cast("string"))

    key = key_of(vid)
    month = F.concat_ws("-", (F.lit(1970) + F.floor((key % 1200) / 12)).cast("string"), F.lpad((key % 12 + 1).cast("string"), 2, "0"))
    copy = F.concat(F.lit("C"), artifact(copied_artifact(vid, host_bits)), F.lit("@"), copy_host(vid, host_bits).cast("string"))
    env = F.concat(F.lit("B"), F.floor(key / 1200).cast("string"), F.lit("/"), month)
    named = F.when(code_of(vid).isin(BASE, RELEASE), artifact(vid)).when(code_of(vid) == COPY, copy).when(code_of(vid) == ENV, env)
    for code, letters in ((STEP, "T"), (STORAGE, "HS"), (BUILDER, "HC")):
        named = named.when(code_of(vid) == code, F.concat(F.lit(letters), key.cast("string")))
    return named
