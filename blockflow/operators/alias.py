"""Alias normalisation: collection, cleaning, set similarity, merging, canonical names, bands, review, knowledge base."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from blockflow.operators.components import connected_components

#: Generic words of names, and accented letters with their plain forms.
GENERIC = ("the", "group", "team")
ACCENTS = ("áàâäéèêëíìîïóòôöúùûüñç", "aaaaeeeeiiiioooouuuunc")


def clean(name: Column, abbreviations: dict[str, str] | None = None) -> Column:
    """Lower case, plain letters, one space between words, no generic words, abbreviations spelled out."""
    flat = F.trim(F.regexp_replace(F.translate(F.lower(name), *ACCENTS), "[^a-z0-9]+", " "))
    words = F.filter(F.split(flat, " "), lambda w: ~w.isin(*GENERIC) & (w != ""))
    if abbreviations:
        table = F.create_map(*[F.lit(x) for kv in abbreviations.items() for x in kv])
        words = F.transform(words, lambda w: F.coalesce(F.try_element_at(table, w), w))
    return F.array_join(words, " ")


def edit_ratio(a: Column, b: Column) -> Column:
    """100 * (1 - distance / longer length); 100 for two empty names."""
    size = F.greatest(F.length(a), F.length(b))
    return F.when(size == 0, F.lit(100.0)).otherwise(F.round(100 * (1 - F.levenshtein(a, b) / size), 6))


def token_sort(name: Column) -> Column:
    return F.array_join(F.array_sort(F.split(name, " ")), " ")


def set_jaccard(kb: DataFrame) -> DataFrame:
    """(a, b, jaccard, weighted) of entities that share an alias. kb: entity, alias, weight."""
    k = kb.groupBy("entity", "alias").agg(F.max("weight").alias("weight"))
    size = k.groupBy("entity").agg(F.count(F.lit(1)).alias("n"), F.sum("weight").alias("w"))
    left, right = k.select(F.col("entity").alias("a"), "alias", F.col("weight").alias("wa")), k.select(F.col("entity").alias("b"), "alias", F.col("weight").alias("wb"))
    both = left.join(right, "alias").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"), F.sum(F.least("wa", "wb")).alias("ws"))
    j = both.join(size.toDF("a", "na", "sa"), "a").join(size.toDF("b", "nb", "sb"), "b")
    return j.select("a", "b", F.round(F.col("shared") / (F.col("na") + F.col("nb") - F.col("shared")), 6).alias("jaccard"), F.round(F.col("ws") / (F.col("sa") + F.col("sb") - F.col("ws")), 6).alias("weighted"))


def merge(kb: DataFrame, cut: float = 0.5, max_rounds: int = 10) -> DataFrame:
    """(entity, root): entities merge while any pair of merged alias sets reaches the cut."""
    roots = kb.select("entity").distinct().withColumn("root", F.col("entity"))
    for _ in range(max_rounds + 1):
        now = kb.join(roots, "entity").select(F.col("root").alias("entity"), "alias", "weight")
        links = set_jaccard(now).where(F.col("jaccard") >= cut).select("a", "b")
        if links.isEmpty():
            break
        if _ == max_rounds:
            raise RuntimeError(f"entities still merge after {max_rounds} rounds")
        step = connected_components(links)
        roots = roots.join(step.toDF("root", "next"), "root", "left").select("entity", F.coalesce("next", "root").alias("root"))
    return roots


#: What decides on a canonical name, first to last; all of them are columns that pick_canonical makes.
PRIORITY = ("recommended", "weight", "count", "first_use")


def pick_canonical(kb: DataFrame, roots: DataFrame, priority: tuple[str, ...] = PRIORITY) -> DataFrame:
    """Of each merged entity one alias: by recommendation, weight, records and first use in the given order, then by name.

    kb: entity, alias, weight, and where known recommended (boolean) and first_use.
    """
    given = lambda c, other: F.col(c) if c in kb.columns else other
    known = kb.withColumn("cf_rec", given("recommended", F.lit(False))).withColumn("cf_use", given("first_use", F.lit(None).cast("long")))
    n = known.join(roots, "entity").groupBy("root", "alias").agg(F.sum("weight").alias("w"), F.count(F.lit(1)).alias("n"), F.max("cf_rec").alias("rec"), F.min("cf_use").alias("use"))
    keys = {"recommended": F.desc("rec"), "weight": F.desc(F.round("w", 6)), "count": F.desc("n"), "first_use": F.asc_nulls_last("use")}
    order = Window.partitionBy("root").orderBy(*[keys[k] for k in priority], "alias")
    return n.withColumn("place", F.row_number().over(order)).where("place = 1").select("root", F.col("alias").alias("canonical"))


def collect(raw: DataFrame, least: int = 2) -> DataFrame:
    """Relevant entries of (entity, alias, source): names with `least` letters once cleaned that differ; one row a pair, with its sources."""
    named = raw.withColumn("c_entity", clean(F.col("entity"))).withColumn("c_alias", clean(F.col("alias")))
    relevant = (F.length(F.regexp_replace("c_alias", "[^a-z]", "")) >= least) & (F.col("c_alias") != F.col("c_entity"))
    return named.where(relevant).groupBy("c_entity", "c_alias").agg(F.array_sort(F.collect_set("source")).alias("sources"), F.count(F.lit(1)).alias("n")).withColumnsRenamed({"c_entity": "entity", "c_alias": "alias"})


#: Longest piece of a name in the blocking below.
PIECE = 4


def candidates(queries: DataFrame, names: DataFrame) -> DataFrame:
    """Distinct (cq, ck) that can reach a score of 80, by equi-joins; queries: cq, names: ck, cleaned.

    At 80 a name of length n has at most n / 4 edits. Cut into one piece more than that, it keeps a piece whole, which stands
    somewhere in the query; so pieces of the knowledge base meet all short substrings of the queries. Both forms of a name,
    as it is and with sorted words, take part.
    """
    forms = lambda c: F.array(F.struct(F.lit(0).alias("form"), F.col(c).alias("t")), F.struct(F.lit(1).alias("form"), token_sort(F.col(c)).alias("t")))
    q = queries.select("cq").distinct().select("cq", F.inline(forms("cq"))).where("t <> ''")
    k = names.select("ck").distinct().select("ck", F.inline(forms("ck"))).where("t <> ''")
    cut = "transform(sequence(0, length(t) div 4), i -> substring(t, cast(floor(i * length(t) / (length(t) div 4 + 1)) + 1 as int), cast(floor((i + 1) * length(t) / (length(t) div 4 + 1)) - floor(i * length(t) / (length(t) div 4 + 1)) as int)))"
    every = f"array_distinct(flatten(transform(sequence(1, {PIECE}), n -> if(length(t) < n, array(), transform(sequence(1, length(t) - n + 1), i -> substring(t, i, n))))))"
    pieces = k.select("ck", "form", F.explode(F.expr(cut)).alias("piece")).distinct()
    near = F.least(F.length("cq"), F.length("ck")) * 100 >= 80 * F.greatest(F.length("cq"), F.length("ck"))
    return q.select("cq", "form", F.explode(F.expr(every)).alias("piece")).join(pieces, ["form", "piece"]).where(near).select("cq", "ck").distinct()


def score(queries: DataFrame, names: DataFrame) -> DataFrame:
    """query, canonical, score of cleaned names that reach 80: the better of edit and token-sort ratio. Equal names meet first."""
    q, k = queries.withColumn("cq", clean(F.col("query"))), names.withColumn("ck", clean(F.col("canonical")))
    exact = q.join(k, F.col("cq") == F.col("ck")).select("query", "canonical", F.lit(100.0).alias("score"))
    a, b = F.col("cq"), F.col("ck")
    scored = candidates(q, k).where("cq <> ck").withColumn("score", F.greatest(edit_ratio(a, b), edit_ratio(token_sort(a), token_sort(b)))).where("score >= 80")
    return exact.union(scored.join(q, "cq").join(k, "ck").select("query", "canonical", "score"))


def resolve(queries: DataFrame, names: DataFrame, hi: float = 95, lo: float = 80) -> DataFrame:
    """The best name of each query with its band: accept, review or reject."""
    best = score(queries, names).groupBy("query").agg(F.min_by(F.struct("score", "canonical"), F.struct(-F.col("score"), "canonical")).alias("b")).select("query", "b.*")
    out = queries.join(best.where(F.col("score") >= lo), "query", "left").withColumn("score", F.coalesce("score", F.lit(0.0)))
    band = F.when(F.col("score") >= hi, "accept").when(F.col("score") >= lo, "review").otherwise("reject")
    return out.select("query", F.when(band != "reject", F.col("canonical")).alias("canonical"), "score", band.alias("decision"))


def knowledge_base(resolved: DataFrame, aliases: DataFrame) -> DataFrame:
    """canonical, aliases, sources of accepted mappings. aliases: query, source."""
    held = resolved.where("decision = 'accept'").join(aliases, "query")
    return held.groupBy("canonical").agg(F.array_sort(F.collect_set("query")).alias("aliases"), F.array_sort(F.collect_set("source")).alias("sources"))


def review_queue(resolved: DataFrame) -> DataFrame:
    return resolved.where("decision = 'review'").select("query", "canonical", "score")


def apply_decisions(resolved: DataFrame, decisions: DataFrame) -> DataFrame:
    """Resolutions after arbitration. decisions: query, verdict (accept or reject); undecided ones stay."""
    j = resolved.join(decisions.select("query", "verdict"), "query", "left")
    band = F.when(F.col("decision") == "review", F.coalesce("verdict", "decision")).otherwise(F.col("decision"))
    return j.select("query", F.when(band != "reject", F.col("canonical")).alias("canonical"), "score", band.alias("decision"))


def review_subset(resolved: DataFrame, share: float = 0.15) -> DataFrame:
    """The share of mappings with the lowest scores, ties by name; by ranks over counts of scores, so no task sorts them all."""
    some = resolved.where("decision <> 'reject'")
    counts = some.groupBy("score").agg(F.count(F.lit(1)).alias("n"))
    # scores are ratios of short lengths, so few differ
    ahead = counts.withColumn("ahead", F.sum("n").over(Window.orderBy("score").rowsBetween(Window.unboundedPreceding, -1))).select("score", F.coalesce("ahead", F.lit(0)).alias("ahead"))
    total = counts.agg(F.sum("n").alias("total"))
    inside = F.row_number().over(Window.partitionBy("score").orderBy("query"))
    placed = some.join(ahead, "score").withColumn("place", F.col("ahead") + inside).crossJoin(F.broadcast(total))
    return placed.where(F.col("place") <= F.ceil(F.col("total") * share)).select("query", "canonical", "score")


def change_rate(before: DataFrame, after: DataFrame) -> DataFrame:
    """How many mappings arbitration changed, of all."""
    j = before.select("query", F.col("canonical").alias("x")).join(after.select("query", F.col("canonical").alias("y")), "query")
    moved = F.sum((~F.col("x").eqNullSafe(F.col("y"))).cast("int")).cast("long")
    return j.agg(F.count(F.lit(1)).alias("n"), moved.alias("changed"), F.round(moved / F.count(F.lit(1)), 6).alias("rate"))


def lookup(names: DataFrame, kb: DataFrame) -> DataFrame:
    """query -> canonical name, score, known aliases and sources; names: query; kb: as knowledge_base."""
    return resolve(names, kb.select("canonical")).join(kb, "canonical", "left").select("query", "canonical", "score", "decision", "aliases", "sources")


def normalize_labels(df: DataFrame, resolved: DataFrame, label: str) -> DataFrame:
    """df with its label replaced by the canonical name where one is known; the old one stays in raw_<label>."""
    known = resolved.where("canonical is not null").select(F.col("query").alias(label), "canonical")
    return df.join(known, label, "left").withColumn(f"raw_{label}", F.col(label)).withColumn(label, F.coalesce("canonical", label)).drop("canonical")


def write_kb(kb: DataFrame, path: str, version: int) -> None:
    """One JSON line an entity, under the version's folder."""
    kb.withColumn("version", F.lit(version)).write.partitionBy("version").mode("append").json(path)


def read_kb(spark, path: str, version: int | None = None) -> DataFrame:
    """A version of the knowledge base, the latest where none is named."""
    kb = spark.read.schema("canonical string, aliases array<string>, sources array<string>, version int").json(path)
    if version is None:
        version = kb.agg(F.max("version").alias("v")).first()["v"]
    return kb.where(F.col("version") == version).drop("version")
