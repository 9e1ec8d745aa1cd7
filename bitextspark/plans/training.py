"""Plans that train in turns: joint back-translation, alternate distillation, and the ladder of stages."""

from __future__ import annotations

import itertools
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..functions.noise import noise_delete
from ..operators import bleu, classify, ensemble, filters, ngram, rerank, selection
from ..operators.lexical import keep_table
from ..operators.translate import SPECS, Ensemble, ModelSpec, Training, TranslationModel, Weighted, back_translate, decode, distill, fine_tune_many, flip, score_many, train, train_many
from ..sources.bitext import split_portions, tag_origin

ARCHITECTURES = ("base", "relpos", "wide", "revsrc")


def score(model, dev: DataFrame, mode: str = "greedy", **how) -> float:
    """Corpus BLEU of a model over (pair_id, src_toks, tgt_toks): one number to the driver."""
    return score_many({"m": model}, {"d": dev}, mode, **how)["m", "d"]


def pick(pairs: DataFrame) -> DataFrame:
    return pairs.select("pair_id", "src_toks", "tgt_toks")


def noised_lengths(pairs: DataFrame, p: float = 0.05) -> DataFrame:
    """Pairs whose sides lose words by hash, each for itself, so lengths of sources and targets differ."""
    cut = lambda side: noise_delete(F.col(side), F.col("pair_id"), p, f"length-{side}").alias(side)
    return pairs.select("pair_id", cut("src_toks"), cut("tgt_toks"))


@dataclass
class History:
    rows: list[tuple] = field(default_factory=list)


def joint_train(bitext: DataFrame, mono_src: DataFrame, mono_tgt: DataFrame, dev: DataFrame, max_iter: int | None = None, min_gain: float = 0.0, noise: str | None = "input", mode: str = "beam", spec: ModelSpec = SPECS["base"], beam: int = 3) -> tuple[TranslationModel, TranslationModel, History]:
    """Source-to-target and target-to-source models that make data for each other until the first gains no more than min_gain.

    mono_src: (pair_id, src_toks), mono_tgt: (pair_id, tgt_toks). Each round's
    synthetic pairs are written, so a round is one decode and lineage stays
    short. Both directions are trained by the same passes.
    """
    bitext = pick(bitext)

    def both(forward: DataFrame, backward: DataFrame, n: int) -> list[TranslationModel]:
        pairs = forward.withColumn("d", F.lit(0)).unionByName(flip(backward).withColumn("d", F.lit(1)))
        return train_many(pairs, [Training(f"s2t-{n}", spec, F.col("d") == 0), Training(f"t2s-{n}", spec, F.col("d") == 1)], made=F.col("pair_id").rlike("^(bt|ft)[0-9]+-"))

    s2t, t2s = both(bitext, bitext, 0)
    best = score(s2t, dev)
    history = History([(0, best, score(t2s, flip(dev)), 0, 0)])
    for i in itertools.count(1) if max_iter is None else range(1, max_iter + 1):
        made_src = keep_table(back_translate(t2s, mono_tgt, noise, mode, beam=beam).withColumn("pair_id", F.concat(F.lit(f"bt{i}-"), "pair_id")), "bt")
        made_tgt = keep_table(back_translate(s2t, mono_src.withColumnRenamed("src_toks", "tgt_toks"), noise, mode, beam=beam).withColumn("pair_id", F.concat(F.lit(f"ft{i}-"), "pair_id")), "ft")
        new_s2t, new_t2s = both(bitext.unionByName(made_src), bitext.unionByName(flip(made_tgt)), i)
        now = score(new_s2t, dev)
        history.rows.append((i, now, score(new_t2s, flip(dev)), made_src.count(), made_tgt.count()))
        if now <= best + min_gain:
            break
        s2t, t2s, best = new_s2t, new_t2s, now
    return s2t, t2s, history


def distilled(students: dict[str, TranslationModel], mono_src: DataFrame, reference: str | None, least_bleu: float | None, tag: str) -> DataFrame:
    """(pair_id, src_toks, tgt_toks, student): what the ensemble of all other architectures teaches each student."""
    out = None
    for a in students:
        teacher = Ensemble([m for b, m in students.items() if b != a])
        made = distill(teacher, mono_src, reference, least_bleu, mode="greedy").select(F.concat(F.lit(f"{tag}-"), "pair_id").alias("pair_id"), "src_toks", "tgt_toks", F.lit(a).alias("student"))
        out = made if out is None else out.unionByName(made)
    return keep_table(out, "kd")


def alternate_distill(bitext: DataFrame, mono_src: DataFrame, dev: DataFrame, archs: tuple[str, ...] = ARCHITECTURES, max_iter: int | None = None, min_gain: float = 0.0, reference: str | None = None, least_bleu: float | None = 28.0) -> tuple[dict[str, TranslationModel], History]:
    """Each student learns from an ensemble of all other architectures; repeated with the new students until their mean gains nothing."""
    bitext = pick(bitext)

    def students_of(pairs: DataFrame, wheres: list, n: int) -> dict[str, TranslationModel]:
        return dict(zip(archs, train_many(pairs, [Training(f"{a}-{n}", SPECS[a], w) for a, w in zip(archs, wheres, strict=True)], made=F.col("pair_id").startswith("kd")), strict=True))

    def values_of(models: dict[str, TranslationModel]) -> dict[str, float]:
        found = score_many(models, {"dev": dev})
        return {a: found[a, "dev"] for a in models}

    students = students_of(bitext, [None] * len(archs), 0)
    values = values_of(students)
    history = History([(0, a, v, 0) for a, v in values.items()])
    for i in itertools.count(1) if max_iter is None else range(1, max_iter + 1):
        made = distilled(students, mono_src, reference, least_bleu, f"kd{i}")
        sizes = {r["student"]: r["count"] for r in made.groupBy("student").count().collect()}  # a row a student
        pairs = bitext.withColumn("student", F.lit(None).cast("string")).unionByName(made)
        new = students_of(pairs, [F.col("student").isNull() | (F.col("student") == a) for a in archs], i)
        now = values_of(new)
        history.rows += [(i, a, v, sizes.get(a, 0)) for a, v in now.items()]
        if sum(now.values()) <= sum(values.values()) + min_gain:
            break
        students, values = new, now
    return students, history


def greedy_members(models: list[TranslationModel], dev: DataFrame, how: str = "logavg", min_gain: float = 0.0) -> ensemble.SearchTrace:
    """The greedy search with real ensemble decoding; all subsets of a round are decoded by one pass."""
    by = {m.model_id: m for m in models}
    single = score_many(by, {"dev": dev})
    order = sorted(by, key=lambda m: (-single[m, "dev"], m))

    def evaluate(subsets):
        found = score_many({"+".join(s): Ensemble([by[m] for m in s], how) for s in subsets}, {"dev": dev})
        return {s: found["+".join(s), "dev"] for s in subsets}

    return ensemble.greedy_ensemble(order, evaluate, min_gain=min_gain)


def in_domain(pool: DataFrame, inside: DataFrame, share: float = 0.06) -> DataFrame:
    """(pair_id, selectors): the pairs of the pool that cross entropy or the classifier takes for in-domain, a share of the pool each."""
    fit = lambda df, toks, n: keep_table(ngram.fit_counts(df, toks, n), "counts")
    models = {"in_src": fit(inside, "src_toks", 2), "out_src": fit(pool, "src_toks", 2), "in_tgt": fit(inside, "tgt_toks", 3), "out_tgt": fit(pool, "tgt_toks", 3)}
    total = pool.count()
    k = -(-int(share * 100) * total // 100)
    ce = selection.select_lowest(selection.bilingual_ce(pool, models), "ce", k)
    found = classify.train_domain_classifier(inside, pool, min(1.0, 3 * inside.count() / max(1, total)))
    return selection.in_domain_union(("ce", ce), ("classifier", selection.select_highest(classify.score_domain(pool, found), "prob", k)))


def domain_labels(pairs: DataFrame, k: int = 2):
    """A k-means model over hashed sentence vectors and the pairs with its cluster as domain."""
    from pyspark.ml.functions import array_to_vector

    vectors = keep_table(ensemble.hashed_vectors(pairs.withColumn("both", F.concat("src_toks", "tgt_toks")), "both").drop("both"), "vectors").withColumn("features", array_to_vector("vec"))
    model = ensemble.cluster_domains(vectors, k, restarts=3)
    return model, model.transform(vectors).withColumn("domain", F.col("domain").cast("double")).drop("vec", "features")


def with_weights(router, df: DataFrame) -> DataFrame:
    from pyspark.ml.functions import vector_to_array

    return keep_table(router.transform(df).withColumn("weights", vector_to_array("probability")).select(*df.columns, "weights"), "routed")


def ladder(pairs: DataFrame, archs: tuple[str, ...] = ARCHITECTURES, members: int = 10) -> list[tuple[str, str, int, str, float]]:
    """(arch, stage, number, split, BLEU) of the cumulative stages over pairs of several domains (see sources.bitext.domain_bitext).

    1 filtered bitext; 2 back-translated and distilled pairs beside it; 3
    fine-tuning on what cross entropy and the classifier select of all training
    pairs, for in-domain text that lies in no other split; 4 the greedy choice
    among models of all architectures, of all data and of the three best of
    six portions; 5 models of each cluster weighted by a router that reads the
    source; 6 re-ranked n-best lists. dev_a chooses, dev_b and test are only
    reported.
    """
    pairs = keep_table(pairs, "pairs")
    train_rows = filters.FilterCascade.bilingual().apply(pairs.filter("split = 'train'"))
    bitext, other = (keep_table(train_rows.filter(F.col("part") == p), p) for p in ("bitext", "mono"))
    splits = {s: keep_table(pairs.filter(F.col("split") == s), s) for s in ("dev_a", "dev_b", "test")}
    inside = keep_table(pick(pairs.filter("split = 'spare'")), "inside")
    rows: list[tuple[str, str, int, str, float]] = []

    def note(systems: dict[str, object], stage: str, n: int, data=splits, **how) -> dict[tuple[str, str], float]:
        found = score_many(systems, data, **how)
        rows.extend((a, stage, n, s, v) for (a, s), v in found.items())
        return found

    base = pick(bitext)
    both = base.withColumn("d", F.lit(0)).unionByName(flip(base).withColumn("d", F.lit(1)))
    *first, reverse = train_many(both, [*(Training(f"{a}-baseline", SPECS[a], F.col("d") == 0) for a in archs), Training("t2s", SPECS["base"], F.col("d") == 1)])
    first = dict(zip(archs, first, strict=True))
    note(first, "baseline", 1)

    synthetic = back_translate(reverse, other.select("pair_id", "tgt_toks"), "input", "beam", beam=3).withColumn("pair_id", F.concat(F.lit("bt-"), "pair_id"))
    taught = distilled(first, other, "tgt", 28.0, "kd")
    nobody = F.lit(None).cast("string").alias("student")
    every = tag_origin(base.select("*", nobody), "bitext", 0).unionByName(tag_origin(synthetic.select("*", nobody), "back-translated", 1)).unionByName(tag_origin(taught, "distilled", 1))
    every = keep_table(split_portions(every), "every")
    of = lambda a: F.col("student").isNull() | (F.col("student") == a)
    found = train_many(every, [*(Training(f"{a}-augmented", SPECS[a], of(a)) for a in archs), *(Training(f"portion-{p}", SPECS["base"], of("base") & (F.col("portion") == p)) for p in range(6))], made=F.col("generation") > 0)
    more = dict(zip(archs, found, strict=False))
    note(more, "augmented", 2)

    # the three portions whose models do best; more members learn from them
    single = score_many({m.model_id: m for m in found[len(archs) :]}, {"dev_a": splits["dev_a"]})
    portions = sorted(range(6), key=lambda p: (-single[f"portion-{p}", "dev_a"], p))[:3]
    plans = [(a, p) for p in portions for a in archs][: max(0, members - len(archs))]
    others = train_many(every, [Training(f"{a}-without-{p}", SPECS[a], of(a) & F.col("portion").isin([q for q in portions if q != p])) for a, p in plans], made=F.col("generation") > 0) if plans else []

    pool = every.filter("student IS NULL OR student = 'base'").select("pair_id", "src_toks", "tgt_toks").dropDuplicates(["pair_id"])
    pool = keep_table(pool, "pool")
    chosen = keep_table(pool.join(in_domain(pool, inside), "pair_id").drop("selectors").unionByName(inside), "chosen")
    candidates = [*more.values(), *others]
    tuned = fine_tune_many(candidates, chosen, 0.7)
    named = dict(zip(archs, tuned, strict=False))
    note(named, "fine-tuned", 3)

    trace = greedy_members(tuned, splits["dev_a"])
    kept = [m for m in tuned if m.model_id in trace.chosen]
    note({"all": Ensemble(kept)}, "ensemble", 4)

    clusters, labelled = domain_labels(chosen)
    labelled = keep_table(labelled, "labelled")
    domains = range(clusters.getK())
    whole = fine_tune_many([m for m in kept for _ in domains], labelled, 0.7, [F.col("domain") == d for _ in kept for d in domains], [f"{m.model_id}-domain-{d}" for m in kept for d in domains])
    weighted = Weighted([Ensemble(whole[d :: len(domains)]) for d in domains])
    router = ensemble.train_domain_router(labelled, ("src_toks",))
    routed = {s: with_weights(router, df) for s, df in splits.items()}
    note({"all": weighted}, "domain weighted", 5, routed, weights="weights")

    lms = {"inside": ngram.fit_counts(inside, "tgt_toks", 2), "general": ngram.fit_counts(base, "tgt_toks", 2)} | {f"domain{d}": ngram.fit_counts(labelled.filter(F.col("domain") == d), "tgt_toks", 2) for d in domains}
    lists = nbest_rows(weighted, routed, lms)
    w = rerank.kbmira(lists.filter("split = 'dev_a'").select("sent_id", "hyp_rank", "feats", "stats"), epochs=10)
    top = bleu.corpus_bleu(rerank.rerank(lists, w), "sent_id", "hyp", "tgt", ("split",), tokenize="split").collect()  # a row a split
    rows.extend(("all", "re-ranked", 6, r["split"], float(r["bleu"])) for r in top)
    return rows


def nbest_rows(model, splits: dict[str, DataFrame], lms: dict[str, DataFrame], n: int = 5) -> DataFrame:
    """N-best lists of all splits with features and BLEU statistics, ready for MIRA."""
    data = None
    for s, df in splits.items():
        part = df.select("pair_id", "src_toks", "tgt", *(["weights"] if "weights" in df.columns else []), F.lit(s).alias("split"))
        data = part if data is None else data.unionByName(part)
    found = decode(model, data, mode="beam", beam=n, nbest=n, weights="weights" if "weights" in data.columns else None, carry=("src_toks", "tgt", "split"))
    rows = keep_table(found.withColumnsRenamed({"pair_id": "sent_id", "score": "nmt"}), "nbest")
    rows = keep_table(rerank.add_features(rows, lms).withColumn("hyp", F.array_join("hyp_toks", " ")).withColumn("key", F.concat_ws("#", "sent_id", "hyp_rank")), "featured")
    stats = bleu.statistics(rows, "key", "hyp", "tgt", "split").select("key", F.array(*(F.col(c).cast("double") for c in bleu.SUMS)).alias("stats"))
    return keep_table(rows.join(stats, "key"), "lists")


