"""Error rates, width studies, boundary checks and attacks."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilesieve.functions.grams import char_blocks, tile_grams
from tilesieve.functions.measures import is_member
from tilesieve.functions.sizing import bits_for
from tilesieve.operators import joins
from tilesieve.operators.baselines import NARROW, sharing_tile
from tilesieve.operators.bloom import Filter, probe_texts
from tilesieve.operators.joins import small_side
from tilesieve.operators.repeats import bucket_sums, shares_of_windows, stored_texts


def empirical_fpr(texts: DataFrame, filter_: Filter, other: Filter, tiles: DataFrame, *, key: str = "doc_id") -> DataFrame:
    """Hits of ``filter_`` that are no stored gram, over the windows of normalised texts that hold none.

    ``tiles`` are the exact hashes (a, b). A window that ``other``, a filter of the same corpus with other bits, lets
    go is surely none of them; what it or ``filter_`` takes is held against the tiles, so few windows are moved.
    """
    n = filter_.spec.n
    taken = lambda f, claimed: probe_texts(texts, f, key=key, hits_only=True, hashes=True).groupBy("a", "b").agg(F.count("*").alias("c")).withColumn("claimed", F.lit(claimed))
    per = taken(filter_, True).unionByName(taken(other, False)).groupBy("a", "b").agg(F.max("c").alias("c"), F.bool_or("claimed").alias("claimed"))
    joined = per.join(tiles.withColumn("_k", F.lit(True)).hint("merge"), ["a", "b"], "left").withColumn("hit", F.coalesce("_k", F.lit(False)))
    count = lambda where: F.coalesce(F.sum(F.when(where, F.col("c"))), F.lit(0))
    hit, claimed = F.col("hit"), F.col("claimed")
    sums = joined.agg(count(hit).alias("true_hits"), count(claimed & ~hit).alias("false_hits"), count(hit & ~claimed).alias("false_negatives"))
    every = texts.agg(F.coalesce(F.sum(F.greatest(F.lit(0), F.length("text") - n + 1)), F.lit(0)).cast("bigint").alias("windows"))
    fpr = F.round(F.col("false_hits") / F.nullif(F.col("windows") - F.col("true_hits"), F.lit(0)), 8)
    return every.crossJoin(sums).select("windows", "true_hits", "false_hits", "false_negatives", fpr.alias("fpr"))  # a row each


def false_chains(chains: DataFrame, *, min_tiles: int = 2) -> DataFrame:
    """Chains by length on novel text; those of ``min_tiles`` or more are false ones."""
    return chains.agg(F.count("*").alias("chains"), F.count_if(F.col("n_tiles") >= min_tiles).alias("false_chains"), F.coalesce(F.max("n_tiles"), F.lit(0)).cast("bigint").alias("longest"))


def classify(best: DataFrame, docs: DataFrame, *, key: str = "doc_id", threshold: float = 0.9) -> DataFrame:
    """(key, label..., lcs_chars, length, pred)."""
    rows = docs.withColumn("length", F.length("text").cast("bigint")).drop("text")
    return rows.join(best.select(key, "lcs_chars"), key, "left").withColumn("lcs_chars", F.coalesce("lcs_chars", F.lit(0))).withColumn("pred", is_member(F.col("lcs_chars"), F.col("length"), threshold))


def confusion(verdicts: DataFrame, *, label: str = "label", pred: str = "pred") -> DataFrame:
    """tp, fp, fn, tn, precision, recall and F1 of boolean verdicts."""
    a, b = F.col(label), F.col(pred)
    counts = verdicts.agg(F.count_if(a & b).alias("tp"), F.count_if(~a & b).alias("fp"), F.count_if(a & ~b).alias("fn"), F.count_if(~a & ~b).alias("tn"))
    ratio = lambda x, y: F.round(x / F.nullif(y, F.lit(0)), 6)
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    return counts.select("*", ratio(tp, tp + fp).alias("prec"), ratio(tp, tp + fn).alias("recall"), ratio(2 * tp, 2 * tp + fp + fn).alias("f1"))


def duplicate_share(df: DataFrame, widths: tuple[int, ...] = (10, 25, 50), *, stride: int = 1, key: str = "doc_id") -> DataFrame:
    """For each width: share of n-gram occurrences seen twice or more, of distinct grams, and of grams in several documents.

    ``stride`` 0 means the width itself. At stride 1 pieces of text are moved, else hashes of grams.
    """
    out, texts = None, stored_texts(df, key=key) if stride == 1 else None
    for n in widths:
        if stride == 1:
            sums = bucket_sums(texts, shares_of_windows(n), n=n, key=key)
            cell = lambda i: F.sum(F.when(F.col("name") == i, F.col("n")))
            row = sums.agg(cell(0).alias("occurrences"), *[F.coalesce(cell(i + 1), F.lit(0)).alias(c) for i, c in enumerate(("grams", "dup", "dup_grams", "cross"))]).withColumn("n", F.lit(n))
        else:
            hashed = tile_grams(df, key=key, n=n, stride=stride or n).select(key, F.xxhash64("gram").alias("a"), F.xxhash64(F.lit(1), F.col("gram")).alias("b"))
            per = hashed.groupBy("a", "b").agg(F.count("*").alias("c"), (F.min(key) != F.max(key)).alias("many"))
            row = per.agg(F.lit(n).alias("n"), F.sum("c").alias("occurrences"), F.count("*").alias("grams"), F.sum(F.when(F.col("c") > 1, F.col("c")).otherwise(0)).alias("dup"), F.count_if(F.col("c") > 1).alias("dup_grams"), F.count_if("many").alias("cross"))
        share = lambda x, of: F.round(F.col(x) / F.nullif(F.col(of), F.lit(0)), 6)
        row = row.select("n", "occurrences", "grams", share("dup", "occurrences").alias("by_occurrence"), share("dup_grams", "grams").alias("by_distinct"), share("cross", "grams").alias("by_cross_doc"))
        out = row if out is None else out.unionByName(row)
    return out


def fingerprint_strength(df: DataFrame, *, n: int = 50, key: str = "doc_id") -> DataFrame:
    """(key, tiles, unique_tiles): how many of a document's tiles occur in no other document."""
    tiles = tile_grams(df, key=key, n=n).select(key, F.md5("gram").alias("g"))
    owners = tiles.groupBy("g").agg((F.min(key) == F.max(key)).alias("own"))
    return tiles.join(owners, "g").groupBy(key).agg(F.count("*").alias("tiles"), F.count_if("own").alias("unique_tiles"))


def boundary_miss(df: DataFrame, lengths: tuple[int, ...], *, n: int = 50, key: str = "doc_id") -> DataFrame:
    """For each length, over substrings at every offset modulo n of each text: how many hold no whole tile.

    The substring at offset r of a stored text holds a tile iff a multiple of n lies in [r, r + length - n].
    """
    offsets = df.where(F.length("text") >= max(lengths) + n).select(key, F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("r"))
    cells = offsets.withColumn("length", F.explode(F.array(*[F.lit(x) for x in lengths])))
    held = (F.ceil(F.col("r") / n) * n) <= F.col("r") + F.col("length") - n
    return cells.groupBy("length").agg(F.count("*").alias("samples"), F.count_if(~held).alias("misses"), F.round(F.count_if(held) / F.count("*"), 6).alias("hit_share"))


def boundary_probe(df: DataFrame, filter_: Filter, lengths: tuple[int, ...], *, key: str = "doc_id") -> DataFrame:
    """The same by probing the filter with real substrings."""
    n = filter_.spec.n
    offsets = df.where(F.length("text") >= max(lengths) + n).select(key, "text", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("r"))
    cells = offsets.withColumn("length", F.explode(F.array(*[F.lit(x) for x in lengths])))
    named = cells.select(F.concat_ws("/", key, "r", "length").alias("sample"), "length", F.substring("text", F.col("r") + 1, F.col("length")).alias("text"))
    as_is = replace(filter_, spec=replace(filter_.spec, norm="none"))  # a blank at an edge belongs to the substring
    hits = probe_texts(named, as_is, key="sample", hits_only=True).groupBy("sample").agg(F.bool_or("hit").alias("hit"))
    return named.select("sample", "length").join(hits, "sample", "left").groupBy("length").agg(F.count("*").alias("samples"), F.count_if(~F.coalesce("hit", F.lit(False))).alias("misses"))


def permute_tiles(df: DataFrame, *, n: int = 50, seed: str = "", key: str = "doc_id") -> DataFrame:
    """(key, text): each text's whole tiles in the order of a hash; texts without a tile are left out."""
    return df.where(F.length("text") >= n).select(key, permuted(F.col("text"), n=n, seed=seed).alias("text"))


def permuted(text: Column, *, n: int = 50, seed: str = "") -> Column:
    """A text's whole tiles in the order of a hash, row by row: nothing is shuffled."""
    keyed = lambda x, i: F.struct(F.md5(F.concat(F.lit(seed), i.cast("string"))).alias("h"), i.alias("i"), x.alias("gram"))
    return F.array_join(F.transform(F.array_sort(F.transform(char_blocks(text, n), keyed)), lambda x: x["gram"]), "")


def verify_chains(chains: DataFrame, corpus: DataFrame, *, key: str = "doc_id", source: str = "doc_id") -> DataFrame:
    """Chains with ``contiguous``: whether their inferred string is anywhere in the corpus.

    ``chains`` needs ``chain``; only texts that share a tile with a string are looked at, which all that hold it do
    if it is long enough; a shorter string is looked for in all.
    """
    texts = corpus.select(F.col(source).alias("cand"), F.col("text").alias("text"))
    strings = chains.select(F.col("chain").alias("_q")).where("chain is not null").distinct()
    long = strings.where(F.length("_q") >= 2 * NARROW - 1)
    near = sharing_tile(texts, long, key="cand").join(texts, "cand").select("_q", "text")
    far = texts.select("text").crossJoin(small_side(strings.where(F.length("_q") < 2 * NARROW - 1))).select("_q", "text")
    found = near.unionByName(far).where(F.contains("text", "_q")).select(F.col("_q").alias("chain")).distinct().withColumn("_y", F.lit(True))
    return chains.join(found, "chain", "left").withColumn("contiguous", F.coalesce("_y", F.lit(False))).drop("_y")


def extension_attack(member, seed: str, alphabet: str, *, n: int, steps: int) -> str:
    """Grow a known gram one symbol at a time wherever exactly one guess is a member of the filter.

    ``member`` tests a gram. Against all n-grams it rebuilds the text; against tiles it stalls at once.
    """
    text = seed
    for _ in range(steps):
        found = [c for c in alphabet if member(text[-(n - 1) :] + c)]
        if len(found) != 1:
            break
        text += found[0]
    return text


def size_curve(spark, n_items: int, fpps: tuple[float, ...] = (1e-2, 1e-3, 1e-4)) -> DataFrame:
    """(fpp, bits_per_item, n_bytes): what each rate costs at the same number of items."""
    rows = [(p, round(bits_for(1, p), 4), round(bits_for(n_items, p) / 8)) for p in fpps]
    return spark.createDataFrame(rows, "fpp double, bits_per_item double, n_bytes bigint")


#: What a look at the rows can't tell: whether a tool may be handed out to run alone, finds near misses, and may err.
STATED = {"scan of stored text": ("yes", "no", False), "full-text index": ("maybe", "maybe", False), "suffix array": ("yes", "no", False), "tiled Bloom filter": ("yes", "no", True)}


def property_matrix(structures: dict[str, list[DataFrame]], *, key: str = "doc_id") -> DataFrame:
    """What each tool of STATED offers, by the rows of its structure as built over a corpus: it avoids redistribution if
    no row holds text, and has an index if a row names a document. The other columns are stated values."""
    out = None
    for tool, (local, fuzzy, probabilistic) in STATED.items():
        rows = None
        for table in structures[tool]:
            texts = [F.coalesce(F.length(c) > 0, F.lit(False)) for c, kind in table.dtypes if kind == "string"]
            holds = F.array_contains(F.array(*texts), True) if texts else F.lit(False)
            seen = table.agg(F.coalesce(F.bool_or(holds), F.lit(False)).alias("t"), F.coalesce(F.bool_or(F.col(key).isNotNull() if key in table.columns else F.lit(False)), F.lit(False)).alias("k"))
            rows = seen if rows is None else rows.unionByName(seen)
        row = rows.agg((~F.bool_or("t")).alias("avoids_redistribution"), F.bool_or("k").alias("has_index"))
        row = row.select(F.lit(tool).alias("tool"), "avoids_redistribution", F.lit(local).alias("local"), "has_index", F.lit(fuzzy).alias("fuzzy"), F.lit(probabilistic).alias("probabilistic"))
        out = row if out is None else out.unionByName(row)
    return out


def table_bytes(df: DataFrame) -> DataFrame:
    """Bytes of a structure's rows, as it was built."""
    return df.agg(F.coalesce(F.sum(joins.row_bytes(df)), F.lit(0)).cast("bigint").alias("n_bytes"))
