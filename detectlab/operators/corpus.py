"""Choosing and building samples."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from detectlab.sources.tables import cut


def select_classes(samples: DataFrame, *, min_count: int = 1, banned: tuple[str, ...] = (), max_bad_share: float = 1.0) -> DataFrame:
    """Samples of classes with enough rows, not banned, and with few enough labels found wrong. The class table is small and broadcast by size."""
    bad = F.sum(F.when(F.col("trusted") == F.lit(False), 1).otherwise(0)).alias("bad")
    judged = F.count("trusted").alias("judged")
    ok = samples.groupBy("cwe").agg(F.count("*").alias("n"), bad, judged).where((F.col("n") >= min_count) & ~F.col("cwe").isin(*banned) & (F.col("bad") <= max_bad_share * F.col("judged")))
    return samples.join(ok.select("cwe"), "cwe", "left_semi")


def prioritise(samples: DataFrame, top: tuple[str, ...]) -> DataFrame:
    """Adds priority: the class's place in the list, null if it has none."""
    place = F.array_position(F.lit(list(top)), F.col("cwe"))
    return samples.withColumn("priority", F.when(place > 0, place))


def scale_strata(samples: DataFrame, cuts: tuple[int, ...] = (100, 400, 1000)) -> DataFrame:
    """Adds loc (lines) and stratum (0: up to the first cut in tokens, and so on)."""
    stratum = F.lit(0)
    for c in cuts:
        stratum = stratum + (F.col("n_tokens") >= c).cast("int")
    return samples.withColumns({"loc": F.size(F.split("code", "\n")), "stratum": stratum})


def seeded(c: str | Column, seed: int) -> Column:
    """Whole-number hash of an id that other engines can follow."""
    c = F.col(c) if isinstance(c, str) else c
    return (c * 48271 + seed * 16807 + 12345) % 2147483647 * 69621 % 2147483647


def stratified_take(strata: DataFrame, per_stratum: int, seed: int = 1) -> DataFrame:
    """The first rows of each stratum in seeded order; the rank limit is applied before the shuffle too."""
    order = Window.partitionBy("stratum").orderBy(seeded("sample_id", seed), "sample_id")
    return strata.withColumn("n", F.row_number().over(order)).where(F.col("n") <= per_stratum).drop("n")


def keep_long(samples: DataFrame, group: str, share: float = 0.5) -> DataFrame:
    """Rows at or above their group's quantile of tokens."""
    cut = samples.groupBy(group).agg(F.percentile("n_tokens", share).alias("cut"))
    return samples.join(cut, group).where("n_tokens >= cut").drop("cut")


def mix_benign(samples: DataFrame, pairs: DataFrame | None, *, ratio: float | None = 1.0, normal: bool = True, seed: int = 3) -> DataFrame:
    """Vulnerable samples, patched twins, and normal benign ones (ratio of these to the vulnerable). Adds kind."""
    vuln = samples.where("is_vuln").withColumn("kind", F.lit("vulnerable"))
    benign = samples.where("NOT is_vuln")
    out = vuln
    patched = None
    if pairs is not None:
        patched = benign.join(pairs.select(F.col("twin").alias("sample_id")).distinct(), "sample_id", "left_semi")
        out = out.unionByName(patched.withColumn("kind", F.lit("patched")))
    if normal:
        rest = benign if patched is None else benign.join(patched.select("sample_id"), "sample_id", "left_anti")
        if ratio is not None:
            order = rest.withColumn("rk", F.row_number().over(Window.partitionBy("lang").orderBy(seeded("sample_id", seed), "sample_id")))
            want = vuln.groupBy("lang").agg(F.floor(F.count("*") * F.lit(ratio)).alias("want"))
            rest = order.join(want, "lang").where("rk <= want").drop("rk", "want")
        out = out.unionByName(rest.withColumn("kind", F.lit("normal")))
    return out


def twins(samples: DataFrame) -> DataFrame:
    """sample_id, twin: for each vulnerable sample the nearest benign one by id of its language and class, as its patched version."""
    v = samples.where("is_vuln").select("sample_id", "lang", "cls")
    b = samples.where("NOT is_vuln").select(F.col("sample_id").alias("twin"), "lang", "cls")
    return v.join(b, ["lang", "cls"]).groupBy("sample_id").agg(F.min_by("twin", F.struct(F.abs(F.col("twin") - F.col("sample_id")), "twin")).alias("twin"))


def blend_general(train: DataFrame, general: DataFrame, share: float, seed: int = 5) -> DataFrame:
    """train plus a seeded share of general rows (id, text); adds origin."""
    picked = general.where(seeded("id", seed) % 1000 < int(share * 1000))
    return train.select(F.col("sample_id").alias("id"), F.lit("target").alias("origin")).unionByName(picked.select("id", F.lit("general").alias("origin")))


def validate_labels(samples: DataFrame, votes: DataFrame, human: DataFrame, *, doubt: int = 500) -> DataFrame:
    """Adds votes_against (thousandths), verdict_of (human, votes), valid. votes: sample_id, agrees. human: sample_id, ok; it wins."""
    v = votes.groupBy("sample_id").agg((1000 * F.sum((~F.col("agrees")).cast("int")) / F.count("*")).cast("int").alias("votes_against"))
    j = samples.join(v, "sample_id", "left").join(human, "sample_id", "left")
    return j.withColumns({"verdict_of": F.when(F.col("ok").isNotNull(), "human").otherwise("votes"), "valid": F.coalesce("ok", F.coalesce("votes_against", F.lit(0)) < doubt)}).drop("ok")


def review_queue(samples: DataFrame, votes: DataFrame, human: DataFrame, *, doubt: int = 500) -> DataFrame:
    """Samples that the votes doubt and no human has judged, most doubted first by rank."""
    v = votes.groupBy("sample_id").agg((1000 * F.sum((~F.col("agrees")).cast("int")) / F.count("*")).cast("int").alias("votes_against")).where(F.col("votes_against") >= doubt)
    return samples.join(v, "sample_id").join(human, "sample_id", "left_anti")


def infer_class(df: DataFrame, rules: tuple[tuple[str, str], ...], column: str = "code") -> DataFrame:
    """Adds inferred: the class of the first rule (pattern, class) that matches."""
    out = F.lit(None).cast("string")
    for pattern, cls in reversed(rules):
        out = F.when(F.col(column).rlike(pattern), cls).otherwise(out)
    return df.withColumn("inferred", out)


def assemble_snippet(trace: DataFrame, patch: DataFrame, bodies: DataFrame) -> DataFrame:
    """sample_id, snippet, marks: the bodies of functions in the trace or the patch; those in the patch are targets, the others context."""
    t = trace.select("sample_id", "fn_id", F.lit(True).alias("in_trace"))
    p = patch.select("sample_id", "fn_id", F.lit(True).alias("in_patch"))
    fns = t.join(p, ["sample_id", "fn_id"], "full_outer").select("sample_id", "fn_id", F.when(F.col("in_patch"), "target").otherwise("context").alias("kind"))
    rows = fns.join(bodies, "fn_id").groupBy("sample_id").agg(F.array_sort(F.collect_list(F.struct("fn_id", "kind", "code"))).alias("f"))
    return rows.select("sample_id", F.array_join(F.transform("f", lambda x: F.concat(F.lit("// "), x.kind, F.lit(" "), x.fn_id, F.lit("\n"), x.code)), "\n").alias("snippet"), F.transform("f", lambda x: F.concat_ws(":", x.fn_id, x.kind)).alias("marks"))


#: Samples of one trace that are put together in one group at most.
SNIPPETS = 1000


def snippet_digests(samples: DataFrame, traces: DataFrame, patch: DataFrame, bodies: DataFrame) -> DataFrame:
    """sample_id, snippet_sha256, marks: the digest of what assemble_snippet makes, null where no text is known. samples
    (sample_id, trace) name their trace, traces (trace, fn_id) what ran in it.

    Samples of a trace meet its texts in one group (of SNIPPETS samples at most), so a text travels once a group, not once a sample.
    """
    p = patch.where("sample_id IS NOT NULL AND fn_id IS NOT NULL").groupBy("sample_id").agg(F.collect_set("fn_id").alias("patch"))
    s = samples.where("sample_id IS NOT NULL").groupBy("sample_id").agg(F.sort_array(F.collect_set("trace")).alias("names"))
    s = s.join(p, "sample_id", "full_outer").select("sample_id", F.coalesce("names", F.array().cast(s.schema["names"].dataType)).alias("names"), F.coalesce("patch", F.array().cast("array<string>")).alias("patch"))
    s = s.withColumn("trace", F.to_json(F.struct("names")))
    sizes = s.groupBy("trace").agg(F.first("names").alias("names"), F.ceil(F.count("*") / SNIPPETS).cast("int").alias("parts"))
    s = cut(s.join(sizes.select("trace", "parts"), "trace").select("trace", F.pmod(F.xxhash64("sample_id"), "parts").cast("int").alias("part"), "sample_id", "patch"))
    ran = sizes.select("trace", "parts", F.explode("names").alias("name")).join(traces.select(F.col("trace").alias("name"), "fn_id"), "name").select("trace", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), "fn_id", F.lit(True).alias("ran"))
    fns = ran.union(s.select("trace", "part", F.explode("patch").alias("fn_id"), F.lit(False))).groupBy("trace", "part", "fn_id").agg(F.max("ran").alias("ran"))
    texts = fns.join(bodies.select("fn_id", "code"), "fn_id").select("trace", "part", "fn_id", "ran", "code")
    out = "sample_id " + s.schema["sample_id"].dataType.simpleString() + ", snippet_sha256 string, marks array<string>"
    return s.groupBy("trace", "part").cogroup(texts.groupBy("trace", "part")).applyInArrow(_digests, out)


def _digests(samples, texts):
    """Samples and texts of one group: the trace is one buffer, hashed in runs between the places where a patch changes it."""
    import hashlib
    from bisect import bisect_left

    import pyarrow as pa

    def entry(kind: str, fn: str, code: str | None) -> bytes:
        return b"" if code is None else f"\n// {kind} {fn}\n{code}".encode()

    codes: dict[str, list] = {}
    ran = set()
    for fn, code, r in zip(texts["fn_id"].to_pylist(), texts["code"].to_pylist(), texts["ran"].to_pylist(), strict=True):
        codes.setdefault(fn, []).append(code)
        if r:
            ran.add(fn)
    order = sorted(ran)
    for fn in codes:
        codes[fn].sort(key=lambda c: (c is not None, c))
    entries = [b"".join(entry("context", fn, c) for c in codes[fn]) for fn in order]
    starts = [0]
    for e in entries:
        starts.append(starts[-1] + len(e))
    whole = memoryview(b"".join(entries))
    marks = [[f"{fn}:context"] * len(codes[fn]) for fn in order]
    flat = [m for x in marks for m in x]
    at_mark = [0]
    for x in marks:
        at_mark.append(at_mark[-1] + len(x))
    ids, digests, lists = [], [], []
    for sample, patch in zip(samples["sample_id"].to_pylist(), samples["patch"].to_pylist(), strict=True):
        pieces, listed, at = [], [], 0
        for fn in sorted(f for f in patch if f in codes):
            i = bisect_left(order, fn)
            pieces += [whole[starts[at] : starts[i]], memoryview(b"".join(entry("target", fn, c) for c in codes[fn]))]
            listed += flat[at_mark[at] : at_mark[i]] + [f"{fn}:target"] * len(codes[fn])
            at = i + (fn in ran)
        pieces.append(whole[starts[at] :])
        listed += flat[at_mark[at] :]
        if not listed:
            continue
        pieces = [x for x in pieces if len(x)]
        h = hashlib.sha256()
        for k, x in enumerate(pieces):
            h.update(x if k else x[1:])  # without the first line break
        ids.append(sample)
        digests.append(h.hexdigest() if pieces else None)
        lists.append(listed)
    return pa.table({"sample_id": pa.array(ids, samples.schema.field("sample_id").type), "snippet_sha256": pa.array(digests, pa.string()), "marks": pa.array(lists, pa.list_(pa.string()))})


def split_versions(df: DataFrame) -> DataFrame:
    """Two rows of each program: lines marked for the one build only are left out of the other. Odd lines stand for the bad build, every third for the good."""
    lines = F.split("code", "\n")
    bad, good = F.filter(lines, lambda x, i: (i % 3 != 2)), F.filter(lines, lambda x, i: (i % 3 != 1))
    rows = F.array(F.struct(F.lit("bad").alias("version"), F.lit(True).alias("vuln"), F.array_join(bad, "\n").alias("text")), F.struct(F.lit("good").alias("version"), F.lit(False).alias("vuln"), F.array_join(good, "\n").alias("text")))
    return df.select("sample_id", F.inline(rows))


def sanitise(c: Column, leak_words: tuple[str, ...]) -> Column:
    """Comments cut, words that give the label away replaced by NAME, blanks collapsed."""
    c = F.regexp_replace(c, r"(?s)/\*.*?\*/", " ")
    c = F.regexp_replace(c, r"(//|#)[^\n]*", " ")
    c = F.regexp_replace(c, "(?i)(^|[^0-9A-Za-z_])(" + "|".join(leak_words) + ")($|[^0-9A-Za-z_])", "$1NAME$3")
    return F.trim(F.regexp_replace(c, r"[ \t]+", " "))


def page_text(c: Column) -> Column:
    """Text of a page: scripts, styles, comments and tags out, blanks collapsed."""
    c = F.regexp_replace(c, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    c = F.regexp_replace(c, r"(?s)<!--.*?-->", " ")
    c = F.regexp_replace(c, r"<[^>]*>", " ")
    return F.trim(F.regexp_replace(c, r"[ \t\n\r]+", " "))


def composition(samples: DataFrame, by: tuple[str, ...] = ("split", "scale", "lang"), cube: bool = False) -> DataFrame:
    """Rows, classes, unseen classes, benign, vulnerable and mean length of each group."""
    grouped = samples.cube(*by) if cube else samples.groupBy(*by)
    aggs = [
        F.count("*").alias("samples"), F.countDistinct("cwe").alias("classes"), F.countDistinct(F.when(F.col("ood_cwe"), F.col("cwe"))).alias("ood_classes"),
        F.sum(F.when(F.col("is_vuln") == F.lit(False), 1).otherwise(0)).alias("benign"), F.sum(F.when(F.col("is_vuln"), 1).otherwise(0)).alias("vulnerable"),
        F.sum(F.length("code")).alias("chars"), F.sum("n_tokens").alias("tokens")]
    if cube:
        aggs.append(F.grouping_id().alias("gid"))
    return grouped.agg(*aggs)


def apply_annotation(samples: DataFrame, notes: DataFrame) -> DataFrame:
    """cwe from the hand-made table (sample_id, noted) where it has one."""
    return samples.join(notes, "sample_id", "left").withColumn("cwe", F.coalesce("noted", "cwe")).drop("noted")


def inject(vulns: DataFrame, per_project: int) -> DataFrame:
    """project, vulns (array), functions: scenarios of several known bugs in one project."""
    order = Window.partitionBy("project").orderBy(seeded("vuln_id", 11), "vuln_id")
    picked = vulns.select("project", "vuln_id").distinct().withColumn("n", F.row_number().over(order)).where(F.col("n") <= per_project).drop("n")
    joined = picked.join(vulns, ["project", "vuln_id"])
    return joined.groupBy("project").agg(F.array_sort(F.collect_set("vuln_id")).alias("vulns"), F.countDistinct("fn_id").alias("functions"))
