"""Mixing sources to target weights by Poisson replication, in DataFrame functions only.

A source's rate is the mean number of copies of its documents that gives it its share of the bytes of the mixture:
weight * scale * all bytes / bytes of the source. Each document's number of copies is the value at which the Poisson
distribution function of that mean passes a uniform number, which is a hash of the seed, the document's id and its
text; so any run, on any number of machines, gives the same copies. Copies are dealt to partitions by a second hash,
which orders the whole mixture at random: partition p holds the p-th part of its range, so no sampling job and no hot
key arise, also where many rows have one id, or none.

Sources without a weight of their own share one weight (rest); so the table of rates, which is broadcast, has one row
more than there are weights at most.

Defined cases: a null id or text hashes as the text "null"; a null source is without a weight of its own; a null text
has 0 bytes, and a source of 0 bytes gets no copies; rows of one id and one text get as many copies each, in one place of
the order; other columns pass through, also ones that begin with ml_, but for those named like the result's own (copy,
n_copies, shuffle_key), which are replaced; a rate over MAX_RATE is an error.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from minlabel.llm.shared import aside

SEED, MAX_RATE = 7, 1000
#: Production weights; what they leave is for the other sources together.
WEIGHTS = {"src0": 0.12, **{f"src{i}": 0.05 for i in range(1, 11)}, **{f"src{i}": 0.04 for i in range(11, 19)}}
REST = "rest"


def group_of(source: str, weights: dict[str, float]) -> Column:
    return F.when(F.col(source).isin(*weights), F.col(source)).otherwise(F.lit(f"{REST}:"))


def rates(docs: DataFrame, weights: dict[str, float], scale: float = 1.0, source: str = "source", text: str = "text") -> DataFrame:
    """ml_group, ml_rate and ml_steps: the Poisson distribution function at 0, 1, ... until it no longer grows."""
    rest = max(0.0, 1.0 - sum(weights.values()))
    share = F.create_map(*[F.lit(x) for k, w in {**weights, f"{REST}:": rest}.items() for x in (k, float(w))])
    sizes = docs.groupBy(group_of(source, weights).alias("ml_group")).agg(F.sum(F.coalesce(F.octet_length(F.col(text)), F.lit(0)).cast("bigint")).alias("ml_bytes"))
    total = sizes.agg(F.sum("ml_bytes")).first()[0] or 0
    rate = F.when(F.col("ml_bytes") > 0, share[F.col("ml_group")] * F.lit(float(scale)) * F.lit(float(total)) / F.col("ml_bytes")).otherwise(0.0)
    out = sizes.select("ml_group", rate.alias("ml_rate"))
    out = out.withColumn("ml_rate", F.when(F.col("ml_rate") > MAX_RATE, F.raise_error(F.lit(f"a source would be repeated over {MAX_RATE} times"))).otherwise(F.col("ml_rate")))
    # each term from the one before, in logarithms; a rate of 0 has all its mass at 0
    steps = (
        "if(ml_rate = 0, array(1D), aggregate(sequence(0L, cast(ceil(ml_rate + 12 * sqrt(ml_rate) + 30) as bigint)), named_struct('l', -ml_rate, 'c', 0D, 'a', cast(array() as array<double>)), "
        "(s, k) -> named_struct('l', s.l + ln(ml_rate / (k + 1)), 'c', s.c + exp(s.l), 'a', array_append(s.a, s.c + exp(s.l)))).a)"
    )
    return out.withColumn("ml_steps", F.expr(steps))


def uniform(seed: int, *parts: Column) -> Column:
    """52 bits of a hash, as a number from 0 to 1."""
    return _bits(seed, 13, *parts) / F.lit(float(1 << 52))


def _bits(seed: int, digits: int, *parts: Column) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), *[F.coalesce(p.cast("string"), F.lit("null")) for p in parts])), 1, digits), 16, 10).cast("bigint")


def mixed(docs: DataFrame, weights: dict[str, float] | None = None, scale: float = 1.0, seed: int = SEED, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """docs with copy (from 1), n_copies and shuffle_key: a row for each copy, in the order of shuffle_key over all partitions."""
    weights = WEIGHTS if weights is None else weights
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    own = docs.drop("copy", "n_copies", "shuffle_key")
    given, names = aside(own)
    key, source, text = names[key], names[source], names[text]
    # one generated column: neither filters nor loops below it make the digest of a text again
    drawn = F.explode(F.array(F.concat_ws("|", F.coalesce(F.col(key).cast("string"), F.lit("null")), F.coalesce(F.md5(F.col(text)), F.lit("null"))))).alias("ml_doc")
    out = given.select("*", drawn).withColumn("ml_group", group_of(source, weights)).join(F.broadcast(rates(given, weights, scale, source, text)), "ml_group")
    # as the start of the loop, the uniform number is made once for each row
    passed = F.aggregate(
        "ml_steps", F.struct(uniform(seed, F.col("ml_doc")).alias("u"), F.lit(0).alias("n")),
        lambda s, c: F.struct(s["u"].alias("u"), (s["n"] + F.when(c <= s["u"], 1).otherwise(0)).alias("n")), lambda s: s["n"],
    )
    out = out.withColumn("n_copies", passed).drop("ml_steps").where("n_copies > 0").withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("n_copies"))))
    out = out.withColumn("shuffle_key", _bits(seed, 15, F.lit("place"), F.col("ml_doc"), F.col("copy")))
    place = F.least(F.floor(F.col("shuffle_key") / F.lit(float(1 << 60)) * parts), F.lit(parts - 1)).cast("int")
    return out.repartitionById(parts, place).sortWithinPartitions("shuffle_key", key, "copy").select(*[F.col(f"`{names[c]}`").alias(c) for c in own.columns], "copy", "n_copies", "shuffle_key")


def oracle(docs: str = "documents", weights: dict[str, float] | None = None, scale: float = 1.0, seed: int = SEED, columns: str = "doc_id, text, lang, source, n_chars") -> str:
    weights = WEIGHTS if weights is None else weights
    own = ", ".join(f"('{k}', {w!r}::double)" for k, w in {**weights, f"{REST}:": max(0.0, 1.0 - sum(weights.values()))}.items())
    bits = lambda digits, *parts: f"cast('0x' || substr(md5({' || chr(124) || '.join((repr(str(seed)), *parts))}), 1, {digits}) as bigint)"
    doc = "coalesce(cast(doc_id as varchar), 'null') || '|' || coalesce(md5(text), 'null')"
    return f"""
with w(g, share) as (values {own}),
d as (select *, coalesce((select g from w where g = source), '{REST}:') as g from {docs}),
s as (select g, sum(coalesce(strlen(text), 0)) as bytes from d group by g),
r as (select s.g, case when bytes > 0 then share * {float(scale)!r}::double * cast((select sum(bytes) from s) as double) / bytes else 0 end as rate from s join w on s.g = w.g),
p as (select g, k, sum(exp(case when k = 0 then -rate else -rate + k * ln(rate) - lgamma(k + 1) end)) over (partition by g order by k) as c
      from r, (select unnest(range(0, 1400)) as k) where rate > 0 and k <= ceil(rate + 12 * sqrt(rate) + 30)),
n as (select {columns}, g, {bits(13, doc)} / cast({1 << 52} as double) as u from d),
c as (select {columns}, (select count(*) from p where p.g = n.g and p.c <= n.u) as n_copies from n join r on n.g = r.g where rate > 0),
x as (select *, unnest(range(1, n_copies + 1)) as copy from c where n_copies > 0)
select {columns}, cast(copy as integer) as copy, cast(n_copies as integer) as n_copies, {bits(15, "'place'", doc, "cast(copy as varchar)")} as shuffle_key from x"""
