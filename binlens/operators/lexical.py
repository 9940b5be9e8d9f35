"""Lexical profiles: counts and densities of word classes per document and bin; never an input of scoring or selection."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from binlens.functions.hashing import u32

#: Own word lists: dimension -> (family, words of four languages).
LEXICON = {
    "article": ("function", "the a an der die das ein eine le la les un une el los las una"),
    "conjunction": ("function", "and or but und oder aber et ou mais y o pero"),
    "preposition": ("function", "of in to on by for with from von zu in mit für auf de du des dans pour avec par sur del en con por para"),
    "pronoun_1": ("social", "i we my our ich wir mein unser je nous mon notre yo nosotros mi nuestro"),
    "pronoun_2": ("social", "you your du ihr dein euer tu vous ton votre usted vosotros"),
    "pronoun_3": ("social", "he she it they his er sie es sein il elle ils elles él ella ellos"),
    "auxiliary": ("function", "is are was were be have ist sind war sein haben est sont était être avoir es son era ser haber"),
    "negation": ("cognition", "not no never nicht kein nie ne pas jamais no nunca"),
    "mental_state": ("cognition", "think know believe want feel denken wissen glauben penser savoir croire pensar saber creer"),
    "insight": ("cognition", "understand learn see idea reason verstehen lernen sehen idee grund comprendre apprendre voir raison entender aprender ver razón"),
    "certainty": ("cognition", "always sure must certain immer sicher muss toujours sûr doit siempre seguro debe"),
    "past": ("tense", "was were had did went war waren hatte ging était avait fut alla era fue había"),
    "present": ("tense", "is are has does goes ist sind hat geht est sont va es son tiene"),
    "future": ("tense", "will shall soon tomorrow wird bald morgen sera bientôt demain será pronto mañana"),
    "see": ("perception", "see look view sehen blick voir regard ver mirar"),
    "hear": ("perception", "hear sound listen hören klang entendre son oír sonido"),
    "feel": ("perception", "feel touch warm fühlen warm sentir toucher sentir tocar"),
    "affiliation": ("drives", "friend together help freund zusammen hilfe ami ensemble aide amigo juntos ayuda"),
    "achievement": ("drives", "win work best gewinnen arbeit beste gagner travail mieux ganar trabajo mejor"),
    "home": ("lifestyle", "home house family haus familie maison famille casa familia"),
    "money": ("lifestyle", "money pay price geld preis argent prix dinero precio"),
    "body": ("physical", "hand head eye kopf auge main tête mano cabeza ojo"),
    "health": ("physical", "health doctor ill arzt krank santé médecin salud médico"),
    "informal": ("informal", "ok yeah hey lol ja hm bah ouais vale oye"),
    "affect": ("affect", "good bad happy sad love gut schlecht liebe bon mauvais amour bueno malo amor"),
}
#: Dimensions without a reproducible route.
NO_ROUTE = ("part_of_speech", "moral", "risk", "curiosity", "mental_health")
#: Format clusters on the native grid.
CLUSTERS = {"en": "dialogic", "fr": "personal", "de": "expository", "es": "structured"}


#: Composite -> dimensions whose z it averages.
COMPOSITES = {"dialogue": ("pronoun_1", "pronoun_2", "negation"), "social": ("pronoun_2", "pronoun_3"), "mental": ("mental_state",),
    "expository": ("article", "preposition", "conjunction")}


def require_route(dim: str) -> str:
    if dim in NO_ROUTE:
        raise KeyError(f"{dim} has no reproducible route")
    return LEXICON[dim][0]


def pairs() -> list[tuple[str, str, str]]:
    return [(dim, family, w) for dim, (family, ws) in LEXICON.items() for w in dict.fromkeys(ws.split())]


def text_stats(df: DataFrame, words) -> DataFrame:
    t = F.coalesce("text", F.lit(""))
    return df.select("doc_id", F.size(words).cast("long").alias("n_words"), F.length(t).cast("long").alias("n_chars"), F.regexp_count(t,
        F.lit("[.!?]")).cast("long").alias("n_stops"), F.regexp_count(t, F.lit(",")).cast("long").alias("n_commas"), F.regexp_count(t,
        F.lit("\n")).cast("long").alias("n_lines"))


def counts(df: DataFrame, words) -> DataFrame:
    """(doc_id, topic, format, dim, family, count): the lexicon is broadcast; only matching words leave the row."""
    lex = df.sparkSession.createDataFrame(pairs(), "dim string, family string, t string")
    vocabulary = sorted({w for _, _, w in pairs()})  # looked up in a hash set, as the optimizer makes one of a long list
    t = df.select("doc_id", "topic", "format", F.explode(F.filter(words, lambda x: x.isin(*vocabulary))).alias("t"))
    return t.join(F.broadcast(lex), "t").groupBy("doc_id", "topic", "format", "dim", "family").agg(F.count("*").alias("count"))


def bin_matrix(c: DataFrame, sizes: DataFrame) -> DataFrame:
    """(topic, format, dim, family, rate): occurrences per 1,000 words, as a ratio of sums; absent dims are 0."""
    dims = c.sparkSession.createDataFrame([(d, f) for d, (f, _) in LEXICON.items()], "dim string, family string")
    g = c.groupBy("topic", "format", "dim").agg(F.sum("count").alias("count"))
    full = sizes.crossJoin(F.broadcast(dims)).join(g, ["topic", "format", "dim"], "left")  # bins x dims of the lexicon
    return full.select("topic", "format", "dim", "family", (1000 * F.try_divide(F.coalesce("count", F.lit(0)).cast("double"),
        F.col("n_words").cast("double"))).alias("rate"))


def doc_mean_matrix(c: DataFrame, docs: DataFrame) -> DataFrame:
    """(topic, format, dim, family, rate): mean over a bin's documents with words of their occurrences per 1,000 words."""
    dims = c.sparkSession.createDataFrame([(d, f) for d, (f, _) in LEXICON.items()], "dim string, family string")
    sizes = docs.where("n_words > 0").groupBy("topic", "format").agg(F.count("*").alias("n_docs"))
    own = c.join(docs.select("doc_id", "n_words"), "doc_id").groupBy("topic", "format", "dim").agg(F.sum(1000 * F.col("count") / F.col("n_words")).alias("total"))
    full = sizes.crossJoin(F.broadcast(dims)).join(own, ["topic", "format", "dim"], "left")  # bins x dims of the lexicon
    return full.select("topic", "format", "dim", "family", (F.coalesce("total", F.lit(0.0)) / F.col("n_docs")).alias("rate"))


def lex_z(m: DataFrame) -> DataFrame:
    w = Window.partitionBy("dim")
    return m.withColumn("lz", F.try_divide(F.col("rate") - F.avg("rate").over(w), F.stddev_pop("rate").over(w)))


def top_bins(bins: DataFrame, k: int = 20) -> DataFrame:
    w = Window.partitionBy("bench").orderBy(F.desc("z"), "topic", "format")
    return bins.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("bench", "topic", "format", "rank", "z")


def proxies(p: DataFrame) -> DataFrame:
    """Four summary proxies around 50 from a bench's mean z by dim (map column ``m``)."""
    z = lambda d: F.coalesce(F.col("m")[d], F.lit(0.0))
    scale = lambda x: 50 + 10 * F.greatest(F.lit(-5.0), F.least(F.lit(5.0), x))
    return p.select(
        "bench", scale(z("article") + z("preposition") - z("pronoun_1") - z("auxiliary") - z("negation")).alias("analytic"),
            scale(z("affect") - z("negation")).alias("tone"),
        scale(z("pronoun_2") - z("pronoun_1")).alias("clout"), scale(z("pronoun_1") + z("mental_state") - z("negation")).alias("authentic"),
    )


def densities(c: DataFrame, sizes: DataFrame) -> DataFrame:
    """(doc_id, dim, density): occurrences per 1,000 words of the document."""
    return c.join(sizes, "doc_id").select("doc_id", "dim", (1000 * F.try_divide(F.col("count").cast("double"), F.col("n_words").cast("double"))).alias("density"))


def wide_matrix(m: DataFrame) -> DataFrame:
    """Bins x dimensions; the columns are the lexicon's, so no pass looks for them."""
    return m.groupBy("topic", "format").agg(*[F.max(F.when(F.col("dim") == d, F.col("rate"))).alias(d) for d in LEXICON])


def bimodal_split(top: DataFrame, least: int = 8) -> DataFrame:
    """Top bins of the interactional and the expository side; bimodal where each side has ``least`` of them."""
    side = F.coalesce(*[F.when(F.col("format") == f, c) for f, c in CLUSTERS.items()])
    a, b = F.count_if(side.isin("dialogic", "personal")), F.count_if(side.isin("expository", "structured"))
    return top.groupBy("bench").agg(a.alias("interactional"), b.alias("expository")).withColumn("bimodal",
        (F.col("interactional") >= least) & (F.col("expository") >= least))


def group_contrast(top: DataFrame, groups: dict[str, tuple], pairs_: list[tuple[str, str]], reps: int, seed: str) -> DataFrame:
    """(a, b, dim, delta, lo, hi): difference of two groups' mean z over their pooled top bins.

    ``top``: bench, rank, dim, lz.  Each group's pooled rows are drawn anew ``reps`` times; sizes are groups x k x dims."""
    name = F.coalesce(*[F.when(F.col("bench").isin(*bs), g) for g, bs in groups.items()])
    rows = top.where("lz is not null").withColumn("grp", name)
    w = Window.partitionBy("grp", "dim")
    rows = rows.withColumn("i", F.row_number().over(w.orderBy("bench", "rank")) - 1).withColumn("n", F.count("*").over(w))
    pick = rows.select("grp", "dim", "n", F.col("i").alias("slot"), F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep"))
    pick = pick.withColumn("i", u32(F.lit(seed), F.col("rep"), F.col("grp"), F.col("slot")) % F.col("n"))
    drawn = pick.join(F.broadcast(rows.select("grp", "dim", "i", "lz")), ["grp", "dim", "i"]).groupBy("rep", "grp", "dim").agg(F.avg("lz").alias("m"))
    seen = rows.groupBy("grp", "dim").agg(F.avg("lz").alias("m")).withColumn("rep", F.lit(-1))
    both = seen.unionByName(drawn)
    which = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b")) for a, b in pairs_])).alias("p")
    cols = both.select("rep", "dim", "grp", "m", which).select("rep", "dim", "grp", "m", "p.*")
    d = cols.groupBy("rep", "dim", "a", "b").agg((F.max(F.when(F.col("grp") == F.col("a"), F.col("m"))) - F.max(F.when(F.col("grp") == F.col("b"),
        F.col("m")))).alias("d"))
    boot = F.when(F.col("rep") >= 0, F.col("d"))
    return d.groupBy("a", "b", "dim").agg(F.max(F.when(F.col("rep") < 0, F.col("d"))).alias("delta"), F.percentile(boot, 0.025).alias("lo"),
        F.percentile(boot, 0.975).alias("hi"))


def claim_tiers() -> list[tuple[str, str, str]]:
    """(family, tier, claim): what may be said of each dimension family; families are those of the lexicon."""
    tiers = {"function": ("descriptive", "style of the supporting bins"), "social": ("supported", "contrast with an interval that excludes 0"),
        "cognition": ("suggestive", "contrast, same sign in most benchmarks"), "affect": ("suggestive", "contrast, same sign in most benchmarks")}
    tiers |= {f: ("exploratory", "descriptive of the given words only") for f in ("tense", "perception", "drives", "lifestyle", "physical", "informal")}
    return [(f, *tiers[f]) for f in sorted({f for f, _ in LEXICON.values()})] + [(d, "refused", "no reproducible route") for d in NO_ROUTE]


def composites(top: DataFrame) -> DataFrame:
    """(bench, composite, z): mean z of a composite's dimensions over a benchmark's top bins."""
    pairs_ = F.array(*[F.struct(F.lit(c).alias("composite"), F.lit(d).alias("dim")) for c, ds in COMPOSITES.items() for d in ds])
    rows = top.withColumn("p", F.explode(F.filter(pairs_, lambda x: x["dim"] == F.col("dim"))))
    return rows.groupBy("bench", "p.composite").agg(F.avg("lz").alias("z"))


def row_normalised(top: DataFrame) -> DataFrame:
    """(dim, bench, z): each dimension's benchmark means standardised across benchmarks; null where they are equal."""
    m = top.groupBy("dim", "bench").agg(F.avg("lz").alias("m"))
    w = Window.partitionBy("dim")
    return m.select("dim", "bench", F.try_divide(F.col("m") - F.avg("m").over(w), F.stddev_pop("m").over(w)).alias("z"))
