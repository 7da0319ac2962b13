"""One query for each operator, over its whole table, with production parameters; SQL where SQL can say it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pantry.llm import line_dedup, lm_scoring, mixing, packing, quality_rules, secrets, sharding, simhash, topk, toxicity
from pantry.session import table


def _crc(doc_id: str = "doc_id") -> Column:
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")))


def op1_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(table(spark, sf_dir, "documents"), held=2, modulus=7)


def op2_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.mix(table(spark, sf_dir, "documents"), weights=(5, 2, 1), most=3.0)
    return out.select("doc_id", F.col("size").cast("long").alias("size"), F.col("source_size").cast("long").alias("source_size"), "target", F.col("taken").cast("long").alias("taken"))


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"), bits=4, shingle=4, seed=42)


def op4_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = topk.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0, k=5, scale=256)
    return out.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"), _crc() % 5 != 0, max_rows=4000)
    return toxicity.score(docs, model).select("doc_id", (_crc() % 5 == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.drop_frequent_lines(table(spark, sf_dir, "documents"), min_docs=5, min_chars=40)
    kept = F.sha2(F.coalesce(F.col("text"), F.lit("")).cast("binary"), 256)
    return out.select("doc_id", "n_lines", "n_dropped", kept.alias("kept_sha256"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(packing.with_lengths(table(spark, sf_dir, "documents")), buckets=12, budget=65536)


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.shard(table(spark, sf_dir, "documents"), shards=16)
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(table(spark, sf_dir, "documents"))
    of = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")
    shown = F.array_join(F.transform("spans", lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    return found.select("doc_id", of("assign").alias("n_assign"), of("access").alias("n_access"), of("hex").alias("n_hex"), "base_sha256", shown.alias("spans"))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality_rules.ledger(table(spark, sf_dir, "documents"))
    base = ~quality_rules.passes(quality_rules.BASE)
    kept = ~base & quality_rules.passes(quality_rules.STANDARD)
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", base.alias("base_failed"), kept.alias("kept"), "failures")


def quality_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.ablations(quality_rules.ledger(table(spark, sf_dir, "documents")))


# What SQL can say of the operators whose whole rows it cannot: the same operators' columns, over whole tables.


def lm_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = op1_lm_scoring(spark, sf_dir)
    return out.select("doc_id", "held_out", "n_tokens", "n_known", "train_tokens", F.round("base_score", 4).alias("base_score"))


def mix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document's columns, and whether its source's mix ends within half of its largest document of the target."""
    out = op2_mixing(spark, sf_dir).join(table(spark, sf_dir, "documents").select("doc_id", "source"), "doc_id")
    by = out.groupBy("source").agg(F.sum("taken").alias("all"), F.max("size").alias("most")).withColumnRenamed("source", "s")
    met = out.join(by, F.col("source").eqNullSafe(F.col("s")))
    return met.select("doc_id", "size", "source_size", F.round("target", 4).alias("target"), (F.abs(F.col("all") - F.col("target")) <= F.col("most")).alias("near"), (F.col("taken") <= 3 * F.col("size")).alias("allowed"))


def toxicity_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op5_toxicity(spark, sf_dir).select("doc_id", "held_out", F.col("score").between(0, 1).alias("in_range"), ((F.col("score") >= 0.5).cast("int") == F.col("predicted")).alias("consistent"))


def packing_padding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The padding of the chosen buckets, which no other choice of as many makes less, and documents by whether they fit."""
    out = op7_packing(spark, sf_dir)
    fits = out.groupBy("bucket", "batch").agg(F.count("*").alias("n"), F.max("bucket_len").alias("w")).where((F.col("n") > 1) & (F.col("n") * F.col("w") > 65536))
    return out.agg(F.count("*").alias("documents"), F.sum("padding").alias("padding"), F.countDistinct("bucket").alias("buckets")).crossJoin(fits.agg(F.count("*").alias("overfull")))


def shard_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each document's columns, and whether its shard holds as many bytes as the law asks, within two documents' size."""
    out = op8_sharding(spark, sf_dir)
    by = out.groupBy("shard").agg(F.sum("size").alias("b"), F.count("*").alias("n"), F.max("slot").alias("last"))
    whole = out.agg(F.sum("size").alias("all"), F.max("size").alias("most"))
    met = out.join(by, "shard").crossJoin(F.broadcast(whole))  # one row
    return met.select("doc_id", "size", "text_crc32", (F.abs(F.col("b") - F.col("all") / 16) <= 2 * F.col("most")).alias("near"), (F.col("last") + 1 == F.col("n")).alias("gapless"))


def secrets_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op9_secrets(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


def queries() -> dict:
    own = (op1_lm_scoring, op2_mixing, op3_simhash, op4_topk, op5_toxicity, op6_line_dedup, op7_packing, op8_sharding, op9_secrets, op10_quality_rules)
    return {f.__name__: f for f in (*own, quality_ablations, lm_base, mix_targets, toxicity_split, packing_padding, shard_sizes, secrets_base)}


_STRIP = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
_SPLIT = "string_split(coalesce(text, ''), chr(10))"
_WORDS = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"

_LEDGER = rf"""
    t AS (SELECT doc_id, text, {_WORDS} AS w, {_SPLIT} AS l FROM documents),
    win AS (SELECT doc_id, unnest(range(1, greatest(len(w) - 1, 1))) AS i, w FROM t),
    tri AS (SELECT doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS s FROM win),
    rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, s) AS n FROM tri) WHERE n > 1),
    cov AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM rep, (SELECT unnest([0, 1, 2]) AS k) GROUP BY 1),
    m AS (SELECT t.doc_id, len(w)::BIGINT AS n_words, list_sum([0] || list_transform(w, lambda x: length(x)))::BIGINT AS word_chars,
          (length(coalesce(text, '')) - length(translate(coalesce(text, ''), '#*$%&|<>', '')))::BIGINT AS n_symbols,
          list_filter(l, lambda x: trim(x, {_STRIP}) <> '') AS l, coalesce(cov.n, 0)::BIGINT AS n_repeat_words
          FROM t LEFT JOIN cov USING (doc_id)),
    led AS (SELECT doc_id, n_words, word_chars, n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines, n_repeat_words, len(l)::BIGINT AS n_lines FROM m),
    f AS (SELECT *, (CASE WHEN n_words < 50 THEN 1 ELSE 0 END + CASE WHEN 100 * n_repeat_words > 50 * n_words THEN 2 ELSE 0 END
          + CASE WHEN word_chars < 2 * n_words THEN 4 ELSE 0 END + CASE WHEN word_chars > 25 * n_words THEN 8 ELSE 0 END
          + CASE WHEN 10 * n_symbols > n_words THEN 16 ELSE 0 END + CASE WHEN 2 * n_dup_lines > n_lines THEN 32 ELSE 0 END)::BIGINT AS failures FROM led)
"""


#: crc32 of a text in SQL: the table by its rule, then a step a byte.
_CRC_TABLE = "crc AS MATERIALIZED (SELECT list(c ORDER BY n) AS tab FROM (SELECT n, list_reduce(range(8), lambda c, k: CASE WHEN c & 1 = 1 THEN xor(3988292384, c >> 1) ELSE c >> 1 END, n) AS c FROM range(256) AS t(n)))"


def _crc_of(text: str) -> str:
    octets = f"list_transform(regexp_extract_all(hex(encode({text})), '..'), lambda x: ('0x' || x)::BIGINT)"
    return f"xor(4294967295::BIGINT, list_reduce({octets}, lambda c, b: xor(c >> 8, tab[(xor(c, b) & 255) + 1]), 4294967295::BIGINT))"


_SIZE = f"len({_WORDS})"
_TOKENS = rf"list_append(regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), chr(10))"
_EXACT = 2048
_BODY = "coalesce(text, '')"


def oracle_sql() -> dict[str, str]:
    return {
        "lm_base": f"""WITH {_CRC_TABLE}, d AS (SELECT doc_id, {_crc_of('doc_id::VARCHAR')} % 7 = 2 AS held_out, {_TOKENS} AS w FROM documents, crc),
            e AS (SELECT doc_id, held_out, unnest(w) AS t FROM d), c AS (SELECT t, count(*) AS c FROM e WHERE NOT held_out GROUP BY t), n AS (SELECT sum(c) AS n, count(*) AS v FROM c)
            SELECT doc_id, held_out, count(*)::BIGINT AS n_tokens, count(c.c)::BIGINT AS n_known, any_value(n.n)::BIGINT AS train_tokens, round(sum(log10((coalesce(c.c, 0) + 1) / (n.n + n.v + 1)::DOUBLE)), 4) AS base_score
            FROM e LEFT JOIN c USING (t), n GROUP BY doc_id, held_out""",
        "mix_targets": f"""WITH RECURSIVE d AS (SELECT doc_id, source, {_SIZE}::BIGINT AS size FROM documents),
            s AS (SELECT source, sum(size)::BIGINT AS source_size, [5, 2, 1][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT] AS w FROM d GROUP BY source),
            r AS (SELECT *, row_number() OVER (ORDER BY 3.0::DOUBLE * source_size / w, source NULLS LAST) AS k, sum(source_size) OVER () AS total FROM s),
            f AS (SELECT 0 AS k, any_value(total)::DOUBLE AS free, sum(w)::DOUBLE AS ws FROM r UNION ALL  -- the sources that are full, one after the other
                  SELECT r.k::INT, f.free - 3 * r.source_size, f.ws - r.w FROM f JOIN r ON r.k = f.k + 1 WHERE f.free * r.w / f.ws > 3 * r.source_size),
            l AS (SELECT free / nullif(ws, 0) AS level, k FROM f ORDER BY k DESC LIMIT 1)
            SELECT doc_id, size, source_size, round(CASE WHEN r.k <= l.k THEN 3.0::DOUBLE * source_size ELSE r.w * level END, 4) AS target, true AS near, true AS allowed
            FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source, l""",
        "toxicity_split": f"WITH {_CRC_TABLE} SELECT doc_id, {_crc_of('doc_id::VARCHAR')} % 5 = 0 AS held_out, true AS in_range, true AS consistent FROM documents, crc",
        "packing_padding": f"""WITH RECURSIVE d AS (SELECT {_SIZE} + 1 AS n FROM documents),
            b AS (SELECT max(n)::BIGINT AS n, count(*) AS c, sum(n)::BIGINT AS s FROM (SELECT n, CASE WHEN n <= {_EXACT} THEN n ELSE ceil(n / power(2, floor(log2(n)) - 6)) * power(2, floor(log2(n)) - 6) END AS bin FROM d) GROUP BY bin),
            o AS (SELECT n, row_number() OVER (ORDER BY n) AS j, sum(c) OVER (ORDER BY n) AS c, sum(s) OVER (ORDER BY n) AS s FROM b),
            p AS (SELECT 1 AS k, j, (n * c - s)::DOUBLE AS pad FROM o UNION ALL
                  SELECT k + 1, o.j, min(p.pad + o.n * (o.c - i.c) - (o.s - i.s)) FROM p JOIN o i ON i.j = p.j JOIN o ON o.j > p.j WHERE k < 12 GROUP BY k, o.j)
            SELECT (SELECT count(*) FROM d) AS documents, min(pad)::BIGINT AS padding, least(12, (SELECT count(*) FROM o))::BIGINT AS buckets, 0::BIGINT AS overfull FROM p WHERE j = (SELECT max(j) FROM o)""",
        "shard_sizes": f"WITH {_CRC_TABLE} SELECT doc_id, (octet_length(encode(coalesce(text, ''))) + 1)::BIGINT AS size, {_crc_of(_BODY)} AS text_crc32, true AS near, true AS gapless FROM documents, crc",
        "secrets_base": r"""SELECT doc_id, len(list_filter(regexp_extract_all(coalesce(text, ''), '(?i:password|passwd|secret|token|api_?key)["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 1), lambda x: length(x) >= 8))::BIGINT AS n_assign,
            len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 16))::BIGINT AS n_access, len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: length(x) >= 32))::BIGINT AS n_hex FROM documents""",
        "op4_topk": """
            WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS e FROM embeddings),
            p AS (SELECT q.vec_id AS query_id, v.vec_id, list_sum(list_transform(list_zip(q.e, v.e), lambda z: z[1] * z[2]))::BIGINT AS score
                  FROM v q JOIN v ON q.vec_id <> v.vec_id WHERE q.vec_id % 50 = 0)
            SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM (
                SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM p) WHERE rank <= 5""",
        "op6_line_dedup": f"""
            WITH l AS (SELECT doc_id, unnest({_SPLIT}) AS line, unnest(range(len({_SPLIT}))) AS pos FROM documents),
            k AS (SELECT *, translate(trim(line, {_STRIP}), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
            c AS (SELECT key, max(doc_id) AS keeper FROM k WHERE length(key) >= 40 GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
            m AS (SELECT k.*, c.key IS NOT NULL AND k.doc_id <> c.keeper AS gone FROM k LEFT JOIN c USING (key))
            SELECT doc_id, count(*)::BIGINT AS n_lines, (count(*) FILTER (WHERE gone))::BIGINT AS n_dropped,
                   sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
            FROM m GROUP BY doc_id""",
        "op10_quality_rules": f"""WITH {_LEDGER}
            SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, (failures & 3) <> 0 AS base_failed, failures = 0 AS kept, failures FROM f""",
        "quality_ablations": f"""WITH {_LEDGER}, r AS (SELECT unnest(['few_words', 'repeated_words', 'short_words', 'long_words', 'symbols', 'repeated_lines']) AS rule, unnest([1, 2, 4, 8, 16, 32])::BIGINT AS bit)
            SELECT rule, (count(*) FILTER (WHERE failures & bit <> 0))::BIGINT AS n_failed, (count(*) FILTER (WHERE failures = bit))::BIGINT AS n_only, count(*)::BIGINT AS n_documents FROM f, r GROUP BY rule""",
    }
