"""Name maps: candidates from a lexicon, made one-to-one within each database, checked, inverted and published as views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from xlsql.catalog.spec import DatabaseSpec
from xlsql.functions.text import subwords, to_ascii_snake
from xlsql.session import load_table


def identifiers(meta: DataFrame) -> DataFrame:
    """db_id, kind, source_name: distinct table and column names of each database. Columns that share a name share a row."""
    table = meta.where("column_name is null").select("db_id", F.lit("table").alias("kind"), F.col("table_name").alias("source_name"))
    column = meta.where("column_name is not null").select("db_id", F.lit("column").alias("kind"), F.col("column_name").alias("source_name"))
    return table.unionByName(column).distinct()


def standardize_subterms(meta: DataFrame, votes: DataFrame | None = None) -> DataFrame:
    """subword, n[, localized]: how often each sub-word recurs over all databases; of rival translations (subword, localized) the most voted wins, ties to the first."""
    counts = identifiers(meta).select("source_name").distinct().select(F.explode(subwords(F.col("source_name"))).alias("subword")).groupBy("subword").agg(F.count("*").alias("n"))
    if votes is None:
        return counts
    ranked = votes.groupBy("subword", "localized").agg(F.count("*").alias("v"))
    best = ranked.groupBy("subword").agg(F.min_by("localized", F.struct((-F.col("v")).alias("v"), F.col("localized").alias("l"))).alias("localized"))
    return counts.join(best, "subword", "left")


def translate_identifiers(names: DataFrame, lexicon: DataFrame) -> DataFrame:
    """Add ``candidate``: every sub-word by its lexicon entry (itself where there is none), joined in order, in ASCII snake case."""
    parts = names.select("*", F.posexplode(subwords(F.col("source_name"))).alias("at", "subword"))
    # as many rows as there are distinct sub-words of identifiers, far below what a broadcast bears
    found = parts.join(F.broadcast(lexicon.select("subword", "localized")), "subword", "left").withColumn("word", F.coalesce("localized", "subword"))
    joined = found.groupBy(*names.columns).agg(F.array_sort(F.collect_list(F.struct("at", "word"))).alias("words"))
    return joined.select(*names.columns, to_ascii_snake(F.array_join(F.transform("words", lambda w: w["word"]), "_")).alias("candidate"))


def translate_with_provider(names: DataFrame, provider, meta: DataFrame | None = None) -> DataFrame:
    """Add ``candidate`` as a provider answers; descriptions of the identifiers, where known, go with the name to tell senses apart.

    A failed or empty answer leaves the name itself. What comes back is put into ASCII snake case like any other candidate.
    """
    from xlsql.providers.base import complete

    asked = names
    if meta is not None:
        told = meta.where("description is not null").select("db_id", F.coalesce("column_name", "table_name").alias("source_name"), "description").groupBy("db_id", "source_name").agg(F.min("description").alias("description"))
        asked = names.join(told, ["db_id", "source_name"], "left")
        prompt = F.concat_ws(" : ", "source_name", "description")
    else:
        prompt = F.col("source_name")
    asked = asked.withColumn("prompt", prompt)
    made = complete(asked.select(F.lit("identifier").alias("task"), "prompt"), provider).select("key", "text")
    keyed = asked.withColumn("key", F.md5(F.concat_ws("\x1f", F.lit("identifier"), "prompt", F.lit("")))).join(made, "key", "left")
    answer = F.when(F.trim("text") != "", F.col("text"))
    return keyed.select(*names.columns, to_ascii_snake(F.coalesce(answer, "source_name")).alias("candidate"))


def resolve_collisions(names: DataFrame, rule: str = "suffix", max_rounds: int = 20) -> DataFrame:
    """Make ``candidate`` unique for distinct source names of one kind within each database, as column ``localized``.

    The first source name in order keeps the name; others get a numbered suffix (``suffix``) or their kind in front
    (``qualify``, then suffixes). A suffix may meet another name, so this repeats until counts and distinct counts agree.
    """
    keys = ["db_id", "kind"]
    out = names.withColumn("localized", F.col("candidate"))
    for k in range(max_rounds):
        groups = out.groupBy(*keys).agg(F.count("*").alias("n"), F.countDistinct("localized").alias("d"))
        if groups.where("n <> d").isEmpty():
            return out
        nth = F.row_number().over(Window.partitionBy(*keys, "localized").orderBy(F.length("localized") - F.length("candidate"), "source_name"))
        changed = F.concat("kind", F.lit("_"), "localized") if rule == "qualify" and k == 0 else F.concat("localized", F.lit("_"), F.col("nth").cast("string"))
        out = out.withColumn("nth", nth).withColumn("localized", F.when(F.col("nth") > 1, changed).otherwise(F.col("localized"))).drop("nth")
    raise RuntimeError("collisions were not resolved")


def collision_report(names: DataFrame) -> DataFrame:
    """db_id, kind, candidate, n, sources: candidates that several source names share."""
    groups = names.groupBy("db_id", "kind", "candidate").agg(F.count("*").alias("n"), F.array_sort(F.collect_set("source_name")).alias("sources"))
    return groups.where("n > 1").withColumn("sources", F.array_join("sources", ","))


def build_name_map(meta: DataFrame, lexicon: DataFrame, rule: str = "suffix") -> DataFrame:
    """db_id, kind, source_name, candidate, localized, version."""
    return resolve_collisions(translate_identifiers(identifiers(meta), lexicon), rule).withColumn("version", F.lit(1))


def check_bijection(name_map: DataFrame, meta: DataFrame) -> DataFrame:
    """Violations (db_id, kind, name, problem): names without image, images of several names, images that are no ASCII snake case."""
    missing = identifiers(meta).join(name_map, ["db_id", "kind", "source_name"], "left_anti").select("db_id", "kind", F.col("source_name").alias("name"), F.lit("no image").alias("problem"))
    many = name_map.groupBy("db_id", "kind", "localized").agg(F.countDistinct("source_name").alias("n")).where("n > 1").select("db_id", "kind", F.col("localized").alias("name"), F.lit("several sources").alias("problem"))
    odd = name_map.where(~F.col("localized").rlike("^[a-z_][a-z0-9_]*$")).select("db_id", "kind", F.col("localized").alias("name"), F.lit("not ASCII snake case").alias("problem"))
    return missing.unionByName(many).unionByName(odd)


def invert_map(name_map: DataFrame) -> DataFrame:
    """The inverse map, with source and localized names exchanged."""
    return name_map.select("db_id", "kind", F.col("localized").alias("source_name"), F.col("source_name").alias("localized"), "version")


def as_dict(name_map: DataFrame, db_id: str) -> dict[str, dict[str, str]]:
    """{"table": {...}, "column": {...}} of one database: metadata, as many entries as it has identifiers."""
    out: dict[str, dict[str, str]] = {"table": {}, "column": {}}
    for r in name_map.where(F.col("db_id") == db_id).select("kind", "source_name", "localized").collect():
        out[r["kind"]][r["source_name"]] = r["localized"]
    return out


def publish_localized_views(session: SparkSession, sf_dir: str, db: DatabaseSpec, names: dict[str, dict[str, str]]) -> None:
    """Views under localized names over the same files: full-width renames, so both languages read the same bytes and the plans compare equal.

    Where a faulty map gives two columns of a table one image, the first keeps it and the others are numbered, so that execution shows the fault.
    """
    for t in db.tables:
        df, images = load_table(session, sf_dir, t), []
        for c in df.columns:
            image = names["column"][c]
            images.append(image if image not in images else f"{image}__{len(images) + 1}")
        df.withColumnsRenamed(dict(zip(df.columns, images))).createOrReplaceTempView(names["table"][t])
