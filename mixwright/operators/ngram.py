"""Hashed n-gram proxies for language models: fitted on manifests, scored by joins."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from mixwright.functions.hashing import BITS, CODES, buckets, fewer, packed, text_codes, uniform
from mixwright.functions.storage import checked, kept
from mixwright.functions.text import words

VOCAB = 1 << 14
LAMBDAS = (0.25, 0.70, 0.05)  # bigram, unigram, flat
LAMBDAS3 = (0.15, 0.20, 0.60, 0.05)  # trigram, bigram, unigram, flat


def coded(df: DataFrame, text: str = "text") -> DataFrame:
    """Append ``codes``: the lower-cased words in ``CODES`` buckets, which all that follows takes instead of ``text`` where they are there."""
    return df.withColumn("codes", text_codes(F.lower(F.col(text))))


def codes_of(df: DataFrame, vocab: int, text: str = "text") -> Column:
    """Lower-cased words as buckets."""
    if "codes" not in df.columns or text != "text" or CODES % vocab:
        return text_codes(F.lower(F.col(text))) if vocab == CODES else buckets(words(F.lower(F.col(text))), vocab)
    return F.col("codes") if vocab == CODES else fewer(F.col("codes"), vocab)


def keys_of(df: DataFrame, order: int, vocab: int, text: str = "text") -> Column:
    """The packed n-gram that ends at each position."""
    plain = "codes" in df.columns and text == "text" and CODES % vocab == 0
    return packed(F.col("codes") if plain else codes_of(df, vocab, text), order, vocab)


def tokens(df: DataFrame, id_col: str, vocab: int = VOCAB, text: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, pos, t, and keep): lower-cased words as buckets."""
    return df.select(F.col(id_col).alias("id"), *keep, F.posexplode(codes_of(df, vocab, text)).alias("pos", "t"))


def grams(df: DataFrame, id_col: str, order: int = 2, vocab: int = VOCAB, text: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """Tokens with their predecessors as ``x`` (and ``x2``), built inside the row, so no window or shuffle."""
    w = df.select(F.col(id_col).alias("id"), *keep, codes_of(df, vocab, text).alias("ts"))
    cells = F.transform("ts", lambda t, i: F.struct(i.alias("pos"), t.alias("t"), F.when(i > 0, F.get("ts", i - 1)).alias("x"), F.when(i > 1, F.get("ts", i - 2)).alias("x2")))
    out = w.select("id", *keep, F.explode(cells).alias("c")).select("id", *keep, "c.pos", "c.t", "c.x", "c.x2")
    return out if order > 2 else out.drop("x2")


def fit(docs: DataFrame, man: DataFrame | None = None, order: int = 2, vocab: int = VOCAB, by: tuple[str, ...] = ()) -> dict:
    """Count tables with copies as multiplicities; ``by`` keeps further columns of the manifest as keys of separate models.

    Without a manifest every document counts once.
    """
    if man is None:
        docs = docs.withColumn("copies", F.lit(1))
    else:
        docs = docs.join(man.filter("copies > 0").select("doc_id", "copies", *by), "doc_id")
    rows = grams(docs, "doc_id", order, vocab, keep=("copies", *by))
    pairs = kept(rows.groupBy(*by, "x", "t").agg(F.sum("copies").alias("n")), "ngram-pairs")
    model = {"vocab": vocab, "by": by, "order": order}
    model["uni"] = pairs.groupBy(*by, "t").agg(F.sum("n").alias("n_t"))
    model["bi"] = pairs.filter("x is not null").withColumnRenamed("n", "n_xt")
    model["ctx"] = model["bi"].groupBy(*by, "x").agg(F.sum("n_xt").alias("n_x"))
    model["total"] = model["uni"].groupBy(*by).agg(F.sum("n_t").alias("n_all"))
    if order > 2:
        model["tri"] = kept(rows.filter("x2 is not null").groupBy(*by, "x2", "x", "t").agg(F.sum("copies").alias("n_3")), "ngram-triples")
        model["ctx2"] = model["tri"].groupBy(*by, "x2", "x").agg(F.sum("n_3").alias("n_2"))
    return model


def fit_asked(docs: DataFrame, arrivals: DataFrame, texts: DataFrame, last: int, by: tuple[str, ...] = (), vocab: int = VOCAB) -> dict:
    """``fit`` at order two with keys (by, step) for steps 1 to ``last``, of what scoring ``texts`` asks: their tokens, contexts and pairs, and all totals.

    ``arrivals`` (doc_id, by, step, copies) tells how many copies of a document come in at a step; a step's model counts all that have
    come by then. Texts are hashed once, a document's arrivals are met only by tokens that are asked, and what has come
    is summed over steps in the tables of asked counts.
    """
    keys = [*by, "step"]
    own = grams(texts, texts.columns[0], 2, vocab)
    asked = {
        "uni": own.select("t").distinct(),
        "ctx": own.filter("x is not null").select("x").distinct(),
        "bi": own.filter("x is not null").select("x", "t").distinct(),
    }
    who = arrivals.filter("copies > 0").groupBy("doc_id").agg(F.collect_list(F.struct(*keys, "copies")).alias("who"))
    coded = kept(docs.join(who, "doc_id").select("who", codes_of(docs, vocab).alias("ts")), "ngram-codes")
    steps = F.explode(F.sequence(F.col("step"), F.lit(last))).alias("step")

    def grown(rows: DataFrame, cells: list[str], n, name: str) -> DataFrame:
        """Sums of copies times ``n`` at each arrival, and over all up to each step."""
        came = rows.select(*cells, n.alias("m"), F.explode("who").alias("w")).groupBy(*[F.col(f"w.{k}").alias(k) for k in keys], *cells).agg(F.sum(F.col("w.copies") * F.col("m")).alias("m"))
        return kept(came.select(*by, *cells, "m", steps).groupBy(*keys, *cells).agg(F.sum("m").alias(name)), f"ngram-{name}")

    cells = F.transform("ts", lambda t, i: F.struct(t.alias("t"), F.when(i > 0, F.get("ts", i - 1)).alias("x")))
    tokens_of = coded.select("who", F.explode(cells).alias("c")).select("who", "c.t", "c.x")
    one, model = F.lit(1).cast("long"), {"vocab": vocab, "by": tuple(keys), "order": 2}
    for label, cols, name in (("uni", ["t"], "n_t"), ("ctx", ["x"], "n_x"), ("bi", ["x", "t"], "n_xt")):
        model[label] = grown(tokens_of.join(checked(kept(asked[label], "ngram-asked")), cols), cols, one, name)
    model["total"] = grown(coded.filter(F.size("ts") > 0), [], F.size("ts").cast("long"), "n_all")
    return model


def _log_chance(order: int, vocab: int, n_all, n_t, n_x, n_xt, n_2=None, n_3=None) -> Column:
    """A token without a seen context rests on the unigram, whose mass takes the bigram's share."""
    uni, bi = F.coalesce(n_t, F.lit(0)) / n_all, F.try_divide(F.coalesce(n_xt, F.lit(0)), n_x)
    flat = F.lit(1.0 / vocab)
    if order > 2:
        l3, l2, l1, l0 = LAMBDAS3
        low = F.when(n_x > 0, l2 * bi + l1 * uni).otherwise((l2 + l1) * uni)
        return F.ln(F.when(n_2 > 0, l3 * F.try_divide(F.coalesce(n_3, F.lit(0)), n_2)).otherwise(l3 * uni) + low + l0 * flat)
    l2, l1, l0 = LAMBDAS
    return F.ln(F.when(n_x > 0, l2 * bi + l1 * uni).otherwise((l2 + l1) * uni) + l0 * flat)


def score(model: dict, texts: DataFrame, id_col: str, keep: tuple[str, ...] = (), text: str = "text") -> DataFrame:
    """(id, keep, by, pos, logp)."""
    by, v = list(model["by"]), model["vocab"]
    rows = grams(texts, id_col, model["order"], v, text, keep)
    rows = rows.crossJoin(F.broadcast(model["total"]))  # a row per model
    rows = rows.join(model["uni"], [*by, "t"], "left").join(model["ctx"], [*by, "x"], "left").join(model["bi"], [*by, "x", "t"], "left")
    names = ["n_all", "n_t", "n_x", "n_xt"]
    if model["order"] > 2:
        rows = rows.join(model["ctx2"], [*by, "x2", "x"], "left").join(model["tri"], [*by, "x2", "x", "t"], "left")
        names += ["n_2", "n_3"]
    return rows.select("id", *keep, *by, "pos", _log_chance(model["order"], v, *map(F.col, names)).alias("logp"))


class SideBySide:
    """Models of several manifests, (method, doc_id, copies), that are fitted and asked together.

    A row per packed n-gram holds what each manifest counts of it (c0, c1, ...) and how often each of ``texts`` asks it
    (q_name), so no row is multiplied by methods, shorter n-grams are sums of these rows, and n-grams that are asked
    alike are scored once. Tables of single tokens have at most ``vocab`` rows and are broadcast.
    """

    def __init__(self, docs: DataFrame, man: DataFrame, texts: dict[str, DataFrame], order: int = 2, vocab: int = VOCAB):
        self.order, self.vocab, self.texts = order, vocab, texts
        names = sorted(r[0] for r in man.filter("copies > 0").select("method").distinct().collect()) or [""]  # a row per method
        who = man.filter("copies > 0").groupBy("doc_id").agg(*[F.sum(F.when(F.col("method") == m, F.col("copies")).otherwise(0)).alias(f"c{i}") for i, m in enumerate(names)])
        self.c, self.q = [f"c{i}" for i in range(len(names))], [f"q_{x}" for x in texts]
        none = lambda cols: [F.lit(0).cast("long").alias(x) for x in cols]
        rows = docs.join(checked(kept(who, "manifests-by-document")), "doc_id").select(F.explode(keys_of(docs, order, vocab)).alias("k"), *self.c, *none(self.q))
        for x, df in texts.items():
            rows = rows.unionByName(df.select(F.explode(keys_of(df, order, vocab)).alias("k"), *none(self.c), *[F.lit(int(q == f"q_{x}")).cast("long").alias(q) for q in self.q]))
        self.cells = kept(rows.groupBy("k").agg(*[F.sum(x).alias(x) for x in self.c + self.q]), "ngram-cells")
        self.pairs = self.cells if order == 2 else kept(self._sums(self.cells, self.k_and(2 * BITS), "k"), "ngram-pairs")
        self.uni = kept(self._sums(self.pairs, self.k_and(BITS), "t"), "ngram-tokens")
        self.ctx = kept(self._sums(self.pairs.filter(F.col("k") >= 1 << BITS), F.shiftright("k", BITS), "x"), "ngram-contexts")
        totals = self.uni.agg(*[F.sum(x) for x in self.c]).first()
        #: (number, name, tokens) of the manifests that have tokens.
        self.methods = [(i, m, n) for i, (m, n) in enumerate(zip(names, totals, strict=True)) if n]

    @staticmethod
    def k_and(bits: int) -> Column:
        return F.col("k").bitwiseAND(F.lit((1 << bits) - 1))

    def _sums(self, rows: DataFrame, key: Column, name: str) -> DataFrame:
        """Counts by a part of the key; what no manifest counts is left out."""
        some = F.greatest(F.lit(0), *self.c) > 0
        return rows.filter(some).groupBy(key.alias(name)).agg(*[F.sum(x).alias(x) for x in self.c])

    def scored(self) -> DataFrame:
        """(k, q_name, l0, l1, ...): log-probabilities of the n-grams that are asked."""
        rows = self.cells.filter(F.greatest(F.lit(0), *self.q) > 0).withColumns({"t": self.k_and(BITS), "xt": self.k_and(2 * BITS), "x": F.shiftright("k", BITS).bitwiseAND(F.lit((1 << BITS) - 1)), "before": F.shiftright("k", BITS)})
        named = lambda df, key, to: df.select(F.col(key).alias(to), *[F.col(x).alias(f"{to}_{x}") for x in self.c])
        rows = rows.join(F.broadcast(named(self.uni, "t", "t")), "t", "left").join(F.broadcast(named(self.ctx, "x", "x")), "x", "left")
        if self.order > 2:
            longer = self._sums(self.cells.filter(F.col("k") >= 1 << 2 * BITS), F.shiftright("k", BITS), "before")
            rows = rows.join(named(self.pairs, "k", "xt"), "xt", "left").join(named(longer, "before", "before"), "before", "left")
        of = lambda kind, i: F.col(f"{kind}_c{i}")
        seen = lambda i: (of("xt", i), of("before", i), F.col(f"c{i}")) if self.order > 2 else (F.col(f"c{i}"),)
        logs = [_log_chance(self.order, self.vocab, F.lit(n), of("t", i), of("x", i), *seen(i)).alias(f"l{i}") for i, _, n in self.methods]
        return kept(rows.select("k", *self.q, *logs), "ngram-scores")

    def each(self, df: DataFrame, keep: list[str], value: str, name: str) -> DataFrame:
        """(method, keep, name): a row per method from its column ``value`` + number."""
        if not self.methods:
            return df.select(F.lit("").alias("method"), *keep, F.lit(0.0).alias(name)).limit(0)
        cells = F.array(*[F.struct(F.lit(m).alias("method"), F.col(f"{value}{i}").alias(name)) for i, m, _ in self.methods])
        return df.select(*keep, F.explode(cells).alias("_m")).select("_m.method", *keep, f"_m.{name}")

    def perplexities(self, scored: DataFrame, name: str) -> DataFrame:
        """(method, perplexity) of one of the texts."""
        sums = scored.agg(F.sum(f"q_{name}").alias("n"), *[F.sum(F.col(f"q_{name}") * F.col(f"l{i}")).alias(f"s{i}") for i, _, _ in self.methods])
        return self.each(sums.filter("n > 0"), ["n"], "s", "s").select("method", F.exp(-F.col("s") / F.col("n")).alias("perplexity"))

    def last_words(self, texts: DataFrame) -> dict:
        """The tables, a row per method, that ``last_word_accuracy`` of ``texts`` asks."""
        asked = checked(kept(_last_two(texts, texts.columns[0], self.vocab).select((F.col("x") + 1).cast("long").alias("x")).distinct(), "last-contexts"))
        of = lambda df, keep, name: self.each(df, keep, "c", name).filter(F.col(name) > 0)
        bi = kept(self.pairs.select((self.k_and(BITS) - 1).cast("int").alias("t"), F.shiftright("k", BITS).alias("x"), *self.c).join(asked, "x", "left_semi"), "last-pairs")
        shown = lambda df, x: df.withColumn(x, (F.col(x) - 1).cast("int"))
        uni = of(shown(self.uni, "t"), ["t"], "n_t")
        total = texts.sparkSession.createDataFrame([(m, n) for _, m, n in self.methods], "method string, n_all long")
        return {"vocab": self.vocab, "by": ("method",), "order": 2, "uni": uni, "ctx": of(shown(self.ctx, "x"), ["x"], "n_x"), "bi": of(shown(bi, "x"), ["x", "t"], "n_xt"), "total": total}

    def choice_accuracy(self, scored: DataFrame, asked: DataFrame, name: str) -> DataFrame:
        """``choice_accuracy`` of the endings ``asked``, which are the texts ``name``."""
        rows = asked.select("item", "option", "start", F.posexplode(keys_of(asked, self.order, self.vocab)).alias("pos", "k")).filter("pos >= start")
        rows = rows.join(checked(kept(scored.filter(F.col(f"q_{name}") > 0).drop(*self.q), "ending-scores")), "k")
        return _endings_won(self.each(rows, ["item", "option"], "l", "logp"), ["method"])


def unigram_perplexity(docs: DataFrame, man: DataFrame | None, texts: DataFrame, id_col: str, vocab: int = VOCAB, smooth: float = 0.05) -> DataFrame:
    docs = docs.withColumn("copies", F.lit(1)) if man is None else docs.join(man.select("doc_id", "copies"), "doc_id")
    counts = tokens(docs, "doc_id", vocab, keep=("copies",)).groupBy("t").agg(F.sum("copies").alias("n_t"))
    total = counts.agg(F.sum("n_t").alias("n_all"))
    rows = tokens(texts, id_col, vocab).join(counts, "t", "left").crossJoin(F.broadcast(total))
    p = (1 - smooth) * F.coalesce("n_t", F.lit(0)) / F.col("n_all") + smooth / vocab
    return rows.agg(F.count("*").alias("n"), F.exp(-F.avg(F.ln(p))).alias("perplexity"))


def perplexity(scored: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    return scored.groupBy(*by).agg(F.count("*").alias("n"), F.exp(-F.avg("logp")).alias("perplexity"))


def domain_table(docs: DataFrame, vocab: int = 1 << 10) -> DataFrame:
    """(domain, t, n): the one pass over text that the domain-level optimisers need."""
    return tokens(docs, "doc_id", vocab, keep=("domain",)).groupBy("domain", "t").agg(F.count("*").alias("n"))


def domain_parts(docs: DataFrame, vocab: int = 1 << 10, volumes: tuple[float, ...] = (0.25, 0.5, 1.0), held: float = 0.2, seed: int = 17) -> DataFrame:
    """(domain, part, t, n): part -1 is held out by hash of the id, part k is what the k-th volume of the others adds to the one before."""
    v = uniform("doc_id", seed + 1)
    part = F.when(uniform("doc_id", seed) < held, F.lit(-1))
    for k, share in enumerate(volumes):
        part = part.when(v < share, F.lit(k))
    return tokens(docs.withColumn("part", part), "doc_id", vocab, keep=("domain", "part")).filter("part is not null").groupBy("domain", "part", "t").agg(F.count("*").alias("n"))


def conditional_entropy(docs: DataFrame, vocab: int = VOCAB) -> DataFrame:
    """(domain, entropy) of the next token given the current one."""
    rows = docs.select("domain", F.explode(keys_of(docs, 2, vocab)).alias("k")).filter(F.col("k") >= 1 << BITS)
    pairs = kept(rows.groupBy("domain", "k").agg(F.count("*").alias("n")).withColumn("x", F.shiftright("k", BITS)), "domain-pairs")
    ctx = kept(pairs.groupBy("domain", "x").agg(F.sum("n").alias("n_x")), "domain-contexts")
    total = ctx.groupBy("domain").agg(F.sum("n_x").alias("n_all"))
    joined = pairs.join(checked(ctx), ["domain", "x"]).join(F.broadcast(total), "domain")
    return joined.groupBy("domain").agg(F.sum(-F.col("n") / F.col("n_all") * F.ln(F.col("n") / F.col("n_x"))).alias("entropy"))


def _last_two(texts: DataFrame, id_col: str, vocab: int) -> DataFrame:
    """(id, x, t): the last token but one and the last of each text of two or more."""
    w = texts.select(F.col(id_col).alias("id"), buckets(words(F.lower(F.col("text"))), vocab).alias("ts")).filter(F.size("ts") > 1)
    return w.select("id", F.element_at("ts", -2).alias("x"), F.element_at("ts", -1).alias("t"))


def last_word_accuracy(model: dict, texts: DataFrame, id_col: str) -> DataFrame:
    """(by, n, accuracy): share of texts whose last token is the likeliest after the one before it (ties: the least token)."""
    by = list(model["by"])
    last = _last_two(texts, id_col, model["vocab"]).crossJoin(F.broadcast(model["total"]))  # a row per model
    uni = model["uni"].join(F.broadcast(model["total"]), by) if by else model["uni"].crossJoin(F.broadcast(model["total"]))
    top = uni.groupBy(*by).agg(F.min(F.struct((-F.col("n_t")).alias("k"), "t")).alias("s")).select(*by, F.col("s.t").alias("top_t"), (-F.col("s.k")).alias("top_n"))
    l2, l1, _ = LAMBDAS
    # The best continuation is one seen after x, or else the commonest token overall.
    asked = last.select(*by, "x").distinct()
    seen = model["bi"].join(asked, [*by, "x"]).join(model["ctx"], [*by, "x"]).join(uni, [*by, "t"])
    best = seen.groupBy(*by, "x").agg(F.min(F.struct((-(l2 * F.col("n_xt") / F.col("n_x") + l1 * F.col("n_t") / F.col("n_all"))).alias("k"), "t")).alias("s"))
    got = last.join(best, [*by, "x"], "left")
    got = got.join(F.broadcast(top), by) if by else got.crossJoin(F.broadcast(top))
    guess = F.when(F.col("s").isNull() | (-F.col("s.k") < l1 * F.col("top_n") / F.col("n_all")), F.col("top_t")).otherwise(F.col("s.t"))
    return got.groupBy(*by).agg(F.count("*").alias("n"), F.avg((guess == F.col("t")).cast("double")).alias("accuracy"))


def choices(texts: DataFrame, id_col: str, others: int = 3) -> DataFrame:
    """(item, option, right, text): each item's start with its own second half and with those of ``others`` items at fixed offsets in order of id."""
    half = texts.select(F.col(id_col).alias("item"), words("text").alias("w")).select("item", F.slice("w", 1, F.greatest(F.lit(1), F.floor(F.size("w") / 2)).cast("int")).alias("a"), F.expr("slice(w, int(size(w) div 2) + 1, greatest(1, size(w)))").alias("b"))
    numbered = half.withColumn("nth", F.row_number().over(Window.orderBy("item")) - 1)  # evaluation items, a bounded set
    total = half.agg(F.count("*").alias("k"))
    asked = numbered.crossJoin(F.broadcast(total)).select("item", "a", "nth", "k", F.explode(F.sequence(F.lit(0), F.lit(others))).alias("option"))
    ends = numbered.select(F.col("nth").alias("from_nth"), F.col("b").alias("end"))
    picked = asked.join(ends, (F.col("nth") + F.col("option") * 7) % F.col("k") == F.col("from_nth"))
    return picked.select("item", "option", (F.col("option") == 0).alias("right"), F.concat_ws(" ", F.col("a"), F.col("end")).alias("text"), F.size("a").alias("start"))


def choice_accuracy(model: dict, asked: DataFrame) -> DataFrame:
    """(by, n, accuracy): share of items whose own ending has the best mean log-probability (ties: the least option)."""
    by = list(model["by"])
    keyed = asked.withColumn("key", F.concat_ws("/", F.col("item").cast("string"), F.col("option").cast("string")))
    return _endings_won(score(model, keyed, "key", keep=("item", "option", "start")).filter("pos >= start"), by)


def _endings_won(scored: DataFrame, by: list[str]) -> DataFrame:
    means = scored.groupBy(*by, "item", "option").agg(F.round(F.avg("logp"), 9).alias("m"))
    best = means.groupBy(*by, "item").agg(F.min(F.struct((-F.col("m")).alias("k"), "option")).alias("s"))
    return best.groupBy(*by).agg(F.count("*").alias("n"), F.avg((F.col("s.option") == 0).cast("double")).alias("accuracy"))


def accuracies(model: dict, texts: DataFrame, id_col: str) -> DataFrame:
    """(by, metric, value) of both accuracies and their mean."""
    return with_mean(last_word_accuracy(model, texts, id_col), choice_accuracy(model, choices(texts, id_col)), list(model["by"]))


def with_mean(last: DataFrame, choice: DataFrame, by: list[str]) -> DataFrame:
    both = last.select(*by, F.lit("last_word_accuracy").alias("metric"), F.col("accuracy").alias("value"))
    both = kept(both.unionByName(choice.select(*by, F.lit("choice_accuracy").alias("metric"), F.col("accuracy").alias("value"))), "accuracies")
    return both.unionByName(both.groupBy(*by).agg(F.avg("value").alias("value")).select(*by, F.lit("mean_accuracy").alias("metric"), "value"))
