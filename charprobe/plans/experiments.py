"""The experiment workloads on the given tables: every result row beside the published value.

Large transformers are stood in for by distributional vectors (PPMI and SVD) and by small transformers of our own, so
directions are compared, not digits. Sizes here are those of the registered queries; the functions take larger ones.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import LETTERS
from ..operators import corpus, encode, lm, measure, mlp, pieces, probe, rewrite, stats, tokenize, vocab
from ..sources import checkpointed, spread, table

SEED, DIM, WINDOW, VOCAB = 42, 32, 2, 1500
MERGES = 400
#: Entries of the staged vocabulary.
STAGED = 36_556
CFG = mlp.ProbeConfig(epochs=3)


def language(spark: SparkSession, sf_dir: str, lang: str = "en") -> DataFrame:
    return spread(table(spark, sf_dir, "documents").where(F.col("lang") == lang).select("doc_id", F.lower("text").alias("text")), "doc_id")


def english(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language(spark, sf_dir)


def scrambled_words(docs: DataFrame) -> DataFrame:
    return corpus.words(rewrite.scrambled_documents(docs, SEED))


def word_tokens(words: DataFrame) -> DataFrame:
    return words.select("doc_id", F.col("pos").alias("word_pos"), F.lit(0).alias("sub_pos"), F.col("word").alias("surface"), "has_space", F.length("word").alias("n_letters"))


def held(df: DataFrame) -> DataFrame:
    """df as a local table: for what is bounded by a vocabulary and is read many times."""
    return df.sparkSession.createDataFrame(df.toArrow(), df.schema)


#: Cells that are worked on at the same time: a stage of one task leaves the other cores to them.
AT_ONCE = 6


def at_once(spark: SparkSession, jobs: Sequence[Callable[[], object]], most: int = AT_ONCE) -> list:
    """What the jobs return, in their order; ``most`` of them run at a time, each in a thread of its own."""
    with ThreadPoolExecutor(most) as pool:
        going = [pool.submit(inheritable_thread_target(spark)(j)) for j in jobs]
        try:
            return [g.result() for g in going]
        finally:  # after a failure, those not begun are left out
            for g in going:
                g.cancel()


def numbered(tokens: DataFrame, size: int) -> tuple[DataFrame, int | None, DataFrame]:
    """Target vocabulary of the tokens (rows of them, or documents with ``pieces``), its greatest id, and the documents as ids."""
    listed = "pieces" in tokens.columns
    v = held(vocab.target_vocab(vocab.ranked(pieces.surfaces(pieces.counted(tokens)), size) if listed else vocab.build(tokens, size)))
    top = v.agg(F.max("token_id")).first()[0]
    return v, top, pieces.numbered(tokens, v) if listed else encode.sequences(tokens, v)


def embedded(v: DataFrame, top: int | None, seqs: DataFrame, vectors: str, dim: int, lm_steps: int = 60) -> DataFrame:
    """Vectors of the vocabulary's tokens from documents as ids."""
    if vectors in ("distributional", "symmetric"):
        return held(encode.distributional(seqs, WINDOW, dim, "concat" if vectors == "distributional" else "both", SEED, top=top))
    if vectors not in ("skipgram", "causal", "masked"):
        return {"random": encode.random_vectors, "letters": encode.letter_bag}[vectors](v)
    before = seqs.is_cached
    kept = seqs if before else seqs.persist()
    try:
        if vectors == "skipgram":
            return held(encode.skipgram(kept, dim, WINDOW, SEED))
        c = lm.LmConfig(causal=vectors == "causal", width=dim, seed=SEED)
        return held(lm.vectors(kept.sparkSession, lm.train(kept, (top or 0) + 1, c, 4, lm_steps // 4)[-1][2]))
    finally:
        if not before:
            kept.unpersist()


def fitted(tokens: DataFrame, size: int, vectors: str, dim: int, lm_steps: int = 60) -> tuple[DataFrame, DataFrame]:
    """Target vocabulary of the tokens and its vectors; they are read twice, from what was kept."""
    before = tokens.is_cached
    kept = tokens if before else tokens.persist()
    try:
        v, top, seqs = numbered(kept, size)
        return v, embedded(v, top, seqs, vectors, dim, lm_steps)
    finally:
        if not before:
            kept.unpersist()


def drawn(v: DataFrame, by: Sequence[str] = ("n_letters",), matched: bool = True, folds: str | None = None) -> DataFrame:
    labels = probe.label(v)
    if folds in ("prev", "next"):
        return probe.grouped_sample(labels, 5, folds, SEED)
    if folds == "random":
        return probe.random_folds(probe.sample_matched(labels, SEED, by), 5, SEED, by)
    s = probe.sample_matched(labels, SEED, by) if matched else probe.sample_unmatched(labels, SEED)
    return probe.split_pairs(s, 0.2, SEED, by if matched else ())


def scored(tokens: DataFrame, experiment: str, size: int = VOCAB, most: int | None = None, by: tuple[str, ...] = ("n_letters",), matched: bool = True, vectors: str = "distributional", folds: str | None = None, cfg: mlp.ProbeConfig = CFG, dim: int = DIM, model: str = "network") -> DataFrame:
    """Vocabulary, vectors, sample, probe: the rows of the test sides with has_space."""
    v, x = fitted(tokens, size, vectors, dim)
    return judged(v, x, experiment, most, by, matched, folds, cfg, model)


def judged(v: DataFrame, x: DataFrame, experiment: str, most: int | None = None, by: tuple[str, ...] = ("n_letters",), matched: bool = True, folds: str | None = None, cfg: mlp.ProbeConfig = CFG, model: str = "network") -> DataFrame:
    kept = vocab.max_letters(v, most) if most else v
    pred = mlp.fit_predict(drawn(kept, by, matched, folds), x, cfg, experiment, model)
    return held(pred.join(kept.select(F.col("token_id").cast("long").alias("token_id"), "has_space"), "token_id"))


def cell(pred: DataFrame, experiment: str, column: str, paper: float | None) -> DataFrame:
    return measure.accuracy(pred).select(F.lit(experiment).alias("experiment"), F.lit(column).alias("col_label"), "n", "correct", "accuracy", "low", "high", F.lit(paper).cast("double").alias("paper_value"))


def together(rows: list[DataFrame]) -> DataFrame:
    return reduce(lambda a, b: a.unionByName(b), rows)


def table1_models(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Matched against unmatched lengths: two small transformers, distributional and skip-gram vectors, a given matrix, noise, spelling."""
    given = table(spark, sf_dir, "embeddings")
    paper = {"causal": (66.7, 69.6), "masked": (60.8, 63.3), "random": (50.0, 50.0), "letters": (100.0, 100.0)}
    t = pieces.of_documents(english(spark, sf_dir)).persist()
    v, top, ids = numbered(t, VOCAB)
    seqs = ids.persist()

    def pair(name: str) -> list[DataFrame]:
        x = held(encode.external_vectors(given, v)) if name == "external" else embedded(v, top, seqs, name, DIM)
        return [cell(judged(v, x, "t1", matched=matched), name, "matched" if matched else "unmatched", paper.get(name, (None, None))[not matched]) for matched in (True, False)]

    try:
        seqs.count()
        t.unpersist()
        rows = at_once(spark, [lambda name=name: pair(name) for name in ("skipgram", "causal", "masked", "distributional", "symmetric", "external", "random", "letters")])
    finally:
        t.unpersist()
        seqs.unpersist()
    return together([r for two in rows for r in two])


#: Published accuracy by length class (fixed values).
BY_LENGTH = {3: 80.4, 4: 71.9, 5: 66.7, 6: 63.9, 7: 62.3}


def table2_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    told = F.create_map(*[F.lit(x) for kv in BY_LENGTH.items() for x in kv])
    return measure.accuracy_by_length(scored(word_tokens(corpus.words(english(spark, sf_dir))), "t2")).withColumn("paper_value", told[F.col("length_class")])


def coded_words(words: DataFrame, merges: int = MERGES) -> DataFrame:
    """Each distinct word once with its pieces, worked out once."""
    return checkpointed(tokenize.with_pieces(words.select("word", "has_space").distinct(), tokenize.bpe_merges(words, merges)))


def _bpe(rows: DataFrame, merges: int = MERGES) -> DataFrame:
    """The words of documents by their pieces under rules learnt from the counts of all of them."""
    return pieces.merged(rows, pieces.learnt(rows, merges))


def substituted(rows: DataFrame, rules: list[tuple[str, str]]) -> DataFrame:
    """The words of documents with their subwords under the rules substituted. Every word is kept."""
    found = pieces.counted(pieces.merged(rows, rules)).select(F.array("word").alias("pieces"))
    return pieces.substituted(rows, rules, rewrite.subword_substitution(found, SEED))


def table4_interventions(spark: SparkSession, sf_dir: str, lang: str = "en") -> DataFrame:
    """Subwords and words on the original, the subword-substituted and the letter-scrambled corpus."""
    paper = {("original", "bpe"): 66.7, ("substituted", "bpe"): 53.8, ("scrambled", "bpe"): 58.2, ("original", "word"): 61.2, ("substituted", "word"): 50.0, ("scrambled", "word"): 50.0}
    docs, out = language(spark, sf_dir, lang), []
    original = pieces.of_documents(docs).persist()
    rules = pieces.learnt(original, MERGES)
    swapped, scrambled = substituted(original, rules).persist(), pieces.of_documents(rewrite.scrambled_documents(docs, SEED)).persist()
    for name, rows in (("original", original), ("substituted", swapped), ("scrambled", scrambled)):
        for tokenizer, t in (("bpe", pieces.merged(original, rules) if name == "original" else _bpe(rows)), ("word", rows)):
            out.append(cell(scored(t, "t4"), tokenizer, name, paper[name, tokenizer]))
        rows.unpersist()
    return together(out)


#: Published accuracies by the space before and the letter's place, and of all (fixed values).
PLACES = {"spaced 1": 49.8, "spaced 2": 54.4, "spaced 3": 90.6, "bare 1": 73.8, "bare 2": 61.2, "bare 3": 72.5, "all": 62.4}


def table5_staged(spark: SparkSession, sf_dir: str, letters: str = LETTERS, size: int = STAGED, cfg: mlp.ProbeConfig = CFG, dim: int = DIM) -> DataFrame:
    """Staged merges on scrambled words, against the same tokens resampled in their classes.

    For both: one probe for all positives, and one each for the six groups of positives by the space before the token
    and the letter's place in it. With fewer ``letters`` the alphabet is folded onto them.
    """
    folded = F.translate("text", LETTERS, "".join(letters[i % len(letters)] for i in range(26)))
    rules = [(r["left"], r["right"]) for r in tokenize.staged_merges(spark, SEED, letters).orderBy("rank").collect()]  # a staged vocabulary's
    tokens = pieces.merged(pieces.of_documents(rewrite.scrambled_documents(english(spark, sf_dir), SEED).withColumn("text", folded)), rules).persist()

    def of(name: str) -> list[DataFrame]:
        t = tokens if name == "staged" else pieces.resampled(tokens, pieces.counted(tokens), SEED)
        v, x = fitted(t, size, "distributional", dim)
        by = ("has_space", "n_letters")
        whole = drawn(v, by).withColumn("cell", F.lit("all"))
        grouped = probe.position_groups(probe.label(v)).withColumn("cell", F.concat_ws(" ", F.when(F.col("group_space"), "spaced").otherwise("bare"), F.col("group_pos").cast("string")))
        grouped = probe.split_pairs(probe.sample_matched(grouped, SEED, ("cell", "n_letters")), 0.2, SEED, ("cell", "n_letters"))
        columns = ["cell", "letter", "token_id", "n_letters", "y", "is_test"]
        pred = held(mlp.fit_predict(whole.select(*columns).unionByName(grouped.select(*columns)), x, cfg))
        return [cell(pred.where(F.col("experiment") == label), name, label, paper if name == "staged" else 50.1 if label == "all" else None) for label, paper in PLACES.items()]

    try:
        tokens.count()
        out = at_once(spark, [lambda: of("staged"), lambda: of("resampled")])
    finally:
        tokens.unpersist()
    return together([r for seven in out for r in seven])


def table5_folded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over an alphabet of eight letters, onto which the others are folded: with 1,168 entries instead of 36,556 each
    token is frequent enough on small tables for its neighbours to tell. Not like for like with the published values."""
    return table5_staged(spark, sf_dir, LETTERS[:8], 3000, mlp.ProbeConfig(epochs=10), 48)


def table6_orthography(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fixed-width chunks against merges on tokens of up to three letters, by the space before them and over both."""
    words = pieces.of_documents(english(spark, sf_dir)).persist()
    paper = {("fixed", "with space"): 50.1, ("fixed", "without"): 80.3, ("fixed", "overall"): 68.3, ("bpe", "with space"): 75.3, ("bpe", "without"): 86.2, ("bpe", "overall"): 80.4}

    def of(name: str) -> list[DataFrame]:
        pred = scored(pieces.fixed_width(words) if name == "fixed" else _bpe(words), "t6", most=3, by=("has_space", "n_letters"))
        kinds = ("with space", pred.where("has_space")), ("without", pred.where("not has_space")), ("overall", pred)
        return [cell(rows, name, label, paper[name, label]) for label, rows in kinds]

    try:
        out = at_once(spark, [lambda: of("fixed"), lambda: of("bpe")])
    finally:
        words.unpersist()
    return together([r for three in out for r in three])


def table7_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five folds at random, and with groups of the same neighbour letter kept whole; lemmas; stems; the last two also by merges."""
    words = pieces.of_documents(english(spark, sf_dir)).persist()
    counts = checkpointed(pieces.surfaces(pieces.counted(words)).withColumnRenamed("surface", "word"))  # read by each side of the joins
    lemmas = rewrite.lemmatize(counts).where("lemma <> word")
    lemma, stemmed = pieces.replaced(words, lemmas).persist(), pieces.stemmed(words).persist()
    out = []
    v, x = fitted(words, VOCAB, "distributional", DIM)
    for name, f, p in (("ungrouped", "random", 61.2), ("previous letter", "prev", 57.3), ("next letter", "next", 57.8)):
        out.append(cell(judged(v, x, "t7", folds=f), "word", name, p))
    for name, w, p in (("lemmatized", lemma, 58.2), ("stemmed", stemmed, 57.3)):
        out.append(cell(scored(w, "t7", folds="random"), "word", name, p))
    for name, w in (("ungrouped", words), ("lemmatized", lemma), ("stemmed", stemmed)):
        out.append(cell(scored(_bpe(w), "t7", folds="random"), "bpe", name, None))
    for w in (words, lemma, stemmed):
        w.unpersist()
    return together(out)


def staged_rows(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    merges = tokenize.staged_merges(spark, SEED)
    return tokenize.with_pieces(scrambled_words(english(spark, sf_dir)), merges), stats.merge_strength(merges)


def figure7_strength(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weaker two-letter rules meet more boundaries: rank correlation over 676 pairs, and that of the logs, on scrambled words."""
    rows, strength = staged_rows(spark, sf_dir)
    bounds = held(stats.row_boundary_pairs(rows))
    return stats.strength_vs_boundary(strength, bounds).join(stats.pearson_of_logs(strength, bounds), "pairs")


def figure7_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, strength = staged_rows(spark, sf_dir)
    return stats.binned(strength, stats.row_boundary_pairs(rows)).select("bin", "boundary_freq", "pairs")


def segmentation_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stats.check_segmentation(*staged_rows(spark, sf_dir))


#: Factors: what varies, the control and the treatment, as (table, experiment, column).
FACTORS = [
    ("merge order", "corpus", ("staged", "all"), ("resampled", "all")),
    ("merge rules", "tokenizer", ("bpe", "with space"), ("fixed", "with space")),
    ("orthography", "restriction", ("fixed", "without"), ("fixed", "with space")),
    ("not comparable", "restriction", ("bpe", "without"), ("fixed", "with space")),
]


def contributions(rows: DataFrame) -> DataFrame:
    """The factor summary from measured cells: rows have experiment, col_label, n and accuracy."""
    spark = rows.sparkSession
    named = rows.select(F.concat_ws(" / ", "experiment", "col_label").alias("experiment"), F.when(F.col("experiment").isin("staged", "resampled"), "staged").otherwise(F.col("experiment")).alias("tokenizer"), F.when(F.col("experiment") == "staged", "scrambled").when(F.col("experiment") == "resampled", "resampled").otherwise("original").alias("corpus"), F.col("col_label").alias("restriction"), "n", "accuracy")
    pairs = spark.createDataFrame([(f, v, " / ".join(c), " / ".join(t)) for f, v, c, t in FACTORS], "factor string, varies string, control string, treatment string")
    return measure.contribution(named, pairs)


def factor_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each factor brings, from the cells that these runs measured."""
    five, six = at_once(spark, [lambda: table5_folded(spark, sf_dir), lambda: table6_orthography(spark, sf_dir)])
    return contributions(five.where("col_label = 'all'").unionByName(six))


def size_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy by the vectors' width."""
    t = word_tokens(corpus.words(english(spark, sf_dir))).persist()
    out = [cell(scored(t, "w16", dim=d), "distributional", f"width {d:03d}", None) for d in (16, 32, 64, 128)]
    t.unpersist()
    return together(out)


def training_curve(spark: SparkSession, sf_dir: str, rounds: int = 4, steps: int = 40) -> DataFrame:
    """Loss and accuracy of a small causal and a small masked transformer along their training."""
    kept = word_tokens(corpus.words(english(spark, sf_dir))).persist()
    v = held(vocab.target_vocab(vocab.build(kept, 1000)))
    seqs = encode.sequences(kept, v).persist()
    out, sample = [], held(drawn(v))
    top = (v.agg(F.max("token_id")).first()[0] or 0) + 1
    for name in ("causal", "masked"):
        for step, loss, e in lm.train(seqs, top, lm.LmConfig(causal=name == "causal", seed=SEED), rounds, steps):
            pred = mlp.fit_predict(sample, lm.vectors(spark, e), CFG, name)
            out.append(measure.accuracy(pred).select(F.lit(name).alias("encoder"), F.lit(step).alias("step"), F.lit(float(loss)).alias("loss"), "n", "accuracy"))
    rows = held(together(out))
    seqs.unpersist()
    kept.unpersist()
    return rows


def corpus_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy by the share of the documents that the vectors were learnt from (drawn by a hash of the id)."""
    docs = english(spark, sf_dir)
    share = F.pmod(F.xxhash64(F.lit(SEED), "doc_id"), F.lit(100))
    return together([cell(scored(word_tokens(corpus.words(docs.where(share < p))), "w11"), "distributional", f"{p:03d} %", None) for p in (10, 25, 50, 100)])


def tokenizer_comparison(spark: SparkSession, sf_dir: str, size: int = 500) -> DataFrame:
    """Trained and fixed tokenizers on all words: tokens a word, unknown words, distinct tokens. Each distinct word is encoded
    once and stands for its occurrences."""
    words = corpus.words(english(spark, sf_dir)).persist()
    counts = corpus.word_counts(words).persist()
    logp, _ = tokenize.unigram_model(words, size, 1, 0.5)
    merges = tokenize.bpe_merges(words, size)
    once = lambda split: counts.join(tokenize.encoded_distinct(counts, split), "word")
    rows = {
        "bpe": tokenize.with_pieces(counts, merges),
        "wordpiece": once(tokenize.WordPieceSplit(tokenize.wordpiece_vocab(words, size))),
        "unigram": once(tokenize.UnigramSplit(logp)),
        "unigram sampled": once(tokenize.UnigramSplit(logp, 0.3, SEED)),
        "fixed width": counts.withColumn("pieces", F.regexp_extract_all("word", F.lit(".{1,3}"), F.lit(0))),
        "word": counts.withColumn("pieces", F.array("word")),
    }
    out = held(together([tokenize.piece_stats(r, "freq").select(F.lit(k).alias("tokenizer"), "words", "tokens", "tokens_per_word", "unknown_rate", "types") for k, r in rows.items()]))
    counts.unpersist()
    words.unpersist()
    return out


def languages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scrambled against original words and merges in each language, and the staged rule correlation there."""

    def of(lang: str, name: str) -> DataFrame:
        docs = language(spark, sf_dir, lang)
        words = pieces.of_documents(rewrite.scrambled_documents(docs, SEED) if name == "scrambled" else docs).persist()
        try:
            return cell(scored(_bpe(words), "w14", 800), lang, name, None)
        finally:
            words.unpersist()

    kinds = [(lang, name) for name in ("scrambled", "original") for lang in ("de", "es", "fr")]  # those with more rules to learn from first
    return together(at_once(spark, [lambda k=k: of(*k) for k in kinds]))


def length_prediction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A ridge from vectors to token length: mean absolute error and explained variance on the test side, beside the mean's."""
    v, x = fitted(word_tokens(corpus.words(english(spark, sf_dir))), VOCAB, "distributional", DIM)
    rows = mlp.ridge(v.select(F.col("token_id").cast("long").alias("token_id"), "n_letters", (F.pmod(F.xxhash64(F.lit(SEED), "token_id"), F.lit(5)) == 0).alias("is_test")), x, "n_letters").where("is_test = 1")
    mean = F.avg("target").over(Window.partitionBy())
    got = rows.withColumn("mean", mean)
    return got.agg(F.count("*").alias("n"), F.round(F.avg(F.abs(F.col("target") - F.col("predicted"))), 6).alias("error"), F.round(F.avg(F.abs(F.col("target") - F.col("mean"))), 6).alias("mean_error"), F.round(1 - F.sum((F.col("target") - F.col("predicted")) ** 2) / F.sum((F.col("target") - F.col("mean")) ** 2), 6).alias("explained"))


def spelling_reconstruction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A token's letters from its vector: the letters that the 26 probes say are in it, against those that are. Probes are
    trained on a fifth left out each, over all tokens; beside it the same from vectors that spell."""
    t = word_tokens(corpus.words(english(spark, sf_dir)))
    out = []
    for name in ("distributional", "letters"):
        v, x = fitted(t, 600, name, DIM)
        labels = probe.label(v).withColumn("fold", F.pmod(F.xxhash64(F.lit(SEED), "token_id"), F.lit(5)).cast("int"))
        pred = mlp.fit_predict(labels, x, mlp.ProbeConfig(epochs=15), name)
        per = pred.groupBy("token_id").agg(F.sum(F.when((F.col("y") == 1) & (F.col("p") >= 0.5), 1).otherwise(0)).alias("hit"), F.sum("y").alias("there"), F.sum((F.col("p") >= 0.5).cast("int")).alias("said"))
        out.append(per.agg(F.lit(name).alias("vectors"), F.count("*").alias("tokens"), F.round(F.avg(((F.col("hit") == F.col("there")) & (F.col("said") == F.col("there"))).cast("int")), 6).alias("exact"), F.round(F.sum("hit") / F.sum("there"), 6).alias("recall"), F.round(F.sum("hit") / F.greatest(F.sum("said"), F.lit(1)), 6).alias("precision")))
    return together(out)


#: Substrings with a function in the language, and others of the same lengths.
AFFIXES, OTHERS = ("ing", "ed", "er", "ly", "ion"), ("ang", "od", "ar", "la", "ian")


def affix_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Can one tell which tokens hold an affix, and which some other substring? Length-matched samples, a probe each."""
    v, x = fitted(word_tokens(corpus.words(english(spark, sf_dir))), VOCAB, "distributional", DIM)
    rows = probe.label_substrings(v, [(p, "any") for p in (*AFFIXES, *OTHERS)]).join(v.select("token_id", "has_space", "n_letters"), "token_id").withColumnRenamed("pattern", "letter")
    s = probe.split_pairs(probe.sample_matched(rows, SEED), 0.3, SEED)
    pred = mlp.fit_predict(s, x, mlp.ProbeConfig(epochs=10))
    return measure.accuracy(pred.withColumn("kind", F.when(F.col("letter").isin(*AFFIXES), "affix").otherwise("other")), ["kind"])


def onset_cohesion(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Words of one onset are as near each other as any two, unless meaning or use binds them; spelling vectors as the other end."""
    t = word_tokens(corpus.words(english(spark, sf_dir)))
    out = []
    for name in ("distributional", "random", "letters"):
        v, x = fitted(t, VOCAB, name, DIM)
        out.append(stats.onset_cohesion(x, v).select(F.lit(name).alias("vectors"), F.round("inside", 6).alias("inside"), F.round("between", 6).alias("between"), "tokens"))
    return together(out)


def chance_level(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is reached without knowledge: random vectors, and always saying the commoner label; and a linear probe beside the network."""
    t = word_tokens(corpus.words(english(spark, sf_dir)))
    v, noise = fitted(t, VOCAB, "random", DIM)
    _, x = fitted(t, VOCAB, "distributional", DIM)
    s = drawn(v)
    train = s.where("is_test = 0").groupBy("letter").agg((F.avg("y") > 0.5).cast("int").alias("guess"))
    most = s.where("is_test = 1").join(train, "letter").withColumn("correct", (F.col("y") == F.col("guess")).cast("int"))
    rows = [("random vectors", judged(v, noise, "f1"), 50.0), ("commoner label", most, 50.0), ("linear probe", judged(v, x, "f12", model="linear"), None), ("network", judged(v, x, "f12"), None)]
    return together([cell(p, name, "matched", paper) for name, p, paper in rows])


ALL = (
    table1_models, table2_lengths, table4_interventions, table5_staged, table5_folded, table6_orthography, table7_groups, figure7_strength, figure7_bins, segmentation_check, factor_summary, size_sweep,
    training_curve, corpus_curve, tokenizer_comparison, languages, length_prediction, spelling_reconstruction, affix_probe, onset_cohesion, chance_level,
)
