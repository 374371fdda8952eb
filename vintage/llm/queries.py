"""Queries of the ten operators and of the pipeline, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table


def op1_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .embedding_dedup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "embeddings"))


def op2_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .url_filter import filter_urls

    return filter_urls(table(spark, sf_dir, "pages"))


def op5_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .common import held_out
    from .toxicity import judge, learn

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    grammar = learn(docs, table(spark, sf_dir, "labels"))
    return judge(docs, grammar).select("doc_id", held_out("doc_id").alias("held_out"), F.col("toxicity").alias("score"), F.col("toxic").alias("predicted"))


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack, pieces

    return pack(pieces(table(spark, sf_dir, "documents").select("doc_id", "text")))


def op7_edit_aware_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every whole text before and after three edits of it; only touched regions are encoded again."""
    from .token_counts import apply_edits, build_trees, sample_edits

    docs = table(spark, sf_dir, "documents").select("doc_id", "text").withColumn("edits", sample_edits())
    counted = build_trees(docs).withColumn("before", F.col("n_tokens"))
    return apply_edits(counted).select("doc_id", F.col("before").alias("n_tokens"), F.col("n_tokens").alias("n_tokens_after"), F.char_length("text").cast("long").alias("n_chars_after"), "re_encoded", "edits")


def op8_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .minhash_dedup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .sharding import shard

    out = shard(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", F.col("place").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def op3_word_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .word_bpe import decoded_digests, encode

    return decoded_digests(encode(table(spark, sf_dir, "documents"), plain_scan=True))


def op4_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    import hashlib

    import pyarrow as pa

    from .chat_format import events_of, format_chats, parse, unescape

    cols = ["conv_id", "turn", "role", "text"]
    extra = [(-7, k, role, "</s>[INST] ok [/INST]") for k, role in enumerate(("user", "assistant"))]
    rows = table(spark, sf_dir, "conversations").select(*cols).union(spark.createDataFrame(extra, "conv_id long, turn long, role string, text string"))
    done = format_chats(events_of(rows))

    def digest(batches):
        sha = lambda s: hashlib.sha256(s.encode("utf-8", "surrogatepass")).hexdigest()
        for b in batches:
            out = []
            for conv, text, spans in zip(*(b.column(c).to_pylist() for c in ("conv_id", "formatted", "loss_spans")), strict=True):
                turns = parse(text)
                loss = "".join(unescape(text[s["start"] : s["end"]]) for s in spans)
                out.append((conv, len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss), len(text)))
            names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*out, strict=True)], names)

    return done.mapInArrow(digest, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality_rules import judge, train

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    trees = train(docs, table(spark, sf_dir, "labels"))
    return judge(docs, trees).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "quality_score")


QUERIES = {f.__name__: f for f in (op1_embedding_near_dedup, op2_url_filter, op3_word_bpe, op4_chat_format, op5_toxicity, op6_best_fit_packing, op7_edit_aware_counts, op8_minhash_near_dedup, op9_sharding, op10_quality_rules)}

_RULES = [("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block")]
_RULE_ROWS = ", ".join(f"('{h}', '{p}', '{d}')" for h, p, d in _RULES)
_LOWER = "translate({0}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
#: Host and path by the contract, of a url or a target.
_AFTER = "CASE WHEN contains({0}, '://') THEN substr({0}, instr({0}, '://') + 3) ELSE '' END"
_HOST, _PATH = _LOWER.format(f"regexp_extract({_AFTER}, '^([^/?#]*)', 1)"), f"regexp_extract({_AFTER}, '^[^/?#]*([^?#]*)', 1)"
_FITS = "(({0} = h OR ends_with({0}, '.' || h)) AND starts_with({1}, p))"
_TAIL = "regexp_extract({0}, '^[^:/?#]*://[^/?#]*([^#]*)', 1)"
_SCHEME, _AUTH = _LOWER.format("regexp_extract({0}, '^([^:/?#]*)://', 1)"), _LOWER.format("regexp_extract({0}, '^[^:/?#]*://([^/?#]*)', 1)")
_NODE = f"""CASE WHEN regexp_matches({{0}}, '^[^:/?#]*://') THEN {_SCHEME} || '://' || CASE {_SCHEME} WHEN 'http' THEN regexp_replace({_AUTH}, ':(80)?$', '') WHEN 'https' THEN regexp_replace({_AUTH}, ':(443)?$', '') ELSE {_AUTH} END
 || CASE WHEN {_TAIL} = '' OR starts_with({_TAIL}, '?') THEN '/' ELSE '' END || {_TAIL} END"""
#: Targets without dot segments; those are held against Python's urllib in the tests.
_TARGET = r"""CASE WHEN regexp_matches(t, '^[A-Za-z][A-Za-z0-9+.-]*://') THEN t WHEN t = '' OR starts_with(t, '#') OR regexp_matches(t, '^[A-Za-z][A-Za-z0-9+.-]*:') OR NOT contains(url, '://') THEN NULL
 WHEN starts_with(t, '//') THEN regexp_extract(url, '^([^:/?#]*:)', 1) || t WHEN starts_with(t, '/') THEN regexp_extract(url, '^([^:/?#]*://[^/?#]*)', 1) || t WHEN starts_with(t, '?') THEN regexp_extract(url, '^([^?#]*)', 1) || t
 WHEN regexp_matches(url, '^[^:/?#]*://[^/?#]*/') THEN regexp_extract(url, '^([^:/?#]*://[^?#]*/)', 1) || t ELSE regexp_extract(url, '^([^:/?#]*://[^/?#]*)', 1) || '/' || t END"""
_LINK = r"""regexp_extract(regexp_extract(html, '(?i)<link\b[^>]*\brel\s*=\s*["'']?canonical\b[^>]*>', 0), '(?i)\bhref\s*=\s*["'']?([^"''\s>]+)', 1)"""
_MOVED = r"""regexp_extract(regexp_extract(html, '(?i)<meta\b[^>]*\bhttp-equiv\s*=\s*["'']?refresh\b[^>]*>', 0), '(?i)\burl\s*=\s*["'']?([^"''\s>]+)', 1)"""
_ESCAPED = "replace({0}, chr(92), chr(92) || chr(92))"
for _c in ("<|", "</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>"):
    _ESCAPED = f"replace({_ESCAPED}, '{_c}', '{_c[0]}' || chr(92) || '{_c[1:]}')"

_CLASSES = """sides AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links), reach(a, b) AS (SELECT a, b FROM sides UNION SELECT r.a, e.b FROM reach r JOIN sides e ON e.a = r.b), least AS (SELECT a, least(a, min(b)) AS c FROM reach GROUP BY a)"""

ORACLE_SQL: dict[str, str] = {
    "op1_embedding_near_dedup": f"""WITH RECURSIVE good AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(embedding, lambda x: x != 0)) > 0),
 normed AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS n FROM good), links AS (SELECT x.vec_id AS a, y.vec_id AS b FROM normed x JOIN normed y ON x.vec_id < y.vec_id AND len(x.e) = len(y.e) AND list_dot_product(x.e, y.e) / (x.n * y.n) >= 0.9), {_CLASSES}
 SELECT vec_id, coalesce(m, 0) AS n_links, coalesce(c, vec_id) AS component_id, vec_id = coalesce(c, vec_id) AS kept FROM embeddings LEFT JOIN (SELECT a, count(*) AS m FROM sides GROUP BY a) s ON s.a = vec_id LEFT JOIN least ON least.a = vec_id""",
    "op8_minhash_near_dedup": rf"""WITH RECURSIVE words AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
 sets AS (SELECT doc_id, CASE WHEN len(w) >= 5 THEN list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS g FROM words),
 grams AS (SELECT doc_id, len(g) AS n, unnest(g) AS g FROM sets), pairs AS (SELECT x.doc_id AS a, y.doc_id AS b, x.n AS na, y.n AS nb, count(*) AS i FROM grams x JOIN grams y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY ALL),
 links AS (SELECT a, b FROM pairs WHERE 100 * i >= 85 * (na + nb - i)), {_CLASSES}
 SELECT doc_id, CAST(len(g) AS BIGINT) AS n_shingles, coalesce(c, doc_id) AS component_id, doc_id = coalesce(c, doc_id) AS kept FROM sets LEFT JOIN least ON least.a = doc_id""",
    "op2_url_filter": f"""WITH RECURSIVE rules(h, p, d) AS (VALUES {_RULE_ROWS}),
 hops AS (SELECT url AS a, {_TARGET} AS b FROM (SELECT url, unnest([{_LINK}, {_MOVED}]) AS t FROM pages)), links AS (SELECT {_NODE.format('a')} AS a, {_NODE.format('b')} AS b, a AS ua, b AS ub FROM hops WHERE a IS NOT NULL AND b IS NOT NULL),
 sides AS (SELECT a, b FROM links UNION SELECT b, a FROM links UNION SELECT a, a FROM links UNION SELECT b, b FROM links), reach(a, b) AS (SELECT a, b FROM sides UNION SELECT r.a, e.b FROM reach r JOIN sides e ON e.a = r.b),
 written AS (SELECT a AS node, regexp_replace(ua, '^([^:/?#]*://[^/?#:]*):(80|443)([/?#]|$)', '\\1\\3') AS u FROM links UNION SELECT b, regexp_replace(ub, '^([^:/?#]*://[^/?#:]*):(80|443)([/?#]|$)', '\\1\\3') FROM links),
 own AS (SELECT node, arg_max(d, (length(h || p), h || p)) AS d FROM written JOIN rules ON {_FITS.format(_HOST.format('u'), _PATH.format('u'))} GROUP BY node, u),
 spread AS (SELECT r.a AS node, bool_or(d = 'allow') AS allowed FROM reach r JOIN own ON own.node = r.b GROUP BY 1),
 parts AS (SELECT row_number() OVER () AS n, page_id, {_HOST.format('url')} AS host, {_PATH.format('url')} AS path, {_NODE.format('url')} AS node FROM (SELECT page_id, url FROM pages)),
 ruled AS (SELECT n, arg_max(h || p, (length(h || p), h || p)) AS rule, arg_max(d, (length(h || p), h || p)) AS d FROM parts JOIN rules ON {_FITS.format('host', 'path')} GROUP BY n)
 SELECT page_id, coalesce(host, '') AS host, coalesce(path, '') AS path, rule, coalesce(d, CASE WHEN NOT allowed THEN 'block' END, 'allow') AS verdict FROM parts LEFT JOIN ruled USING (n) LEFT JOIN spread USING (node)""",
    "op4_chat_format": f"""WITH rows AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]')
 SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, md5(text))) AS turns_sha256, CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
 sha256(coalesce(string_agg(text, '' ORDER BY turn, role, md5(text)) FILTER (role = 'assistant'), '')) AS loss_sha256, CAST(sum({len('<|turn|>') + 1 + len('<|end|>') + 1} + length(replace({_ESCAPED.format('role')}, chr(10), chr(92) || chr(10))) + length({_ESCAPED.format('text')})) AS BIGINT) AS formatted_chars FROM rows GROUP BY 1""",
}
