"""The operators' queries with production parameters, each over its whole table, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat_format
from .chat_format import format_chats, read_chats
from .common import table, tokenizer_path
from .decontaminate import contaminated
from .line_dedup import line_removals
from .lm_scoring import cross_entropy_difference
from .near_dedup import near_duplicates
from .packing import pack, token_pieces
from .quality_rules import quality
from .token_count import count_tokens
from .token_output import token_digest, write_tokens
from .warc import read_warc, write_warc


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every (document, benchmark item) where the item occurs within its error budget."""
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op2_pack(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = token_pieces(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), end_id=1, capacity=4096)
    return pack(pieces, 4096)


def op3_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), words=3, percent=85).select("doc_id", "n_shingles", "component_id", "kept")


def op4_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    spoken = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", spoken), (-1, 1, "assistant", spoken)], "conv_id long, turn long, role string, text string")
    chats = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(extra)
    tokenizer = tokenizer_path("byte_bpe_50k.json")
    return read_chats(*format_chats(chats, tokenizer), tokenizer)


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_warc(*write_warc(table(spark, sf_dir, "pages"))).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op6_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The target is every document labelled good and not toxic; the background is all documents."""
    good = table(spark, sf_dir, "labels").where("quality = 1 and coalesce(toxic, 0) = 0")
    return cross_entropy_difference(table(spark, sf_dir, "documents"), good)


def op7_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    gone = line_removals(docs).withColumn("removed", F.array_join(F.col("removed").cast("array<string>"), ","))
    none = {"n_lines": 0, "n_exact": 0, "n_near": 0, "removed": ""}
    return docs.select("doc_id", F.xxhash64("text").alias("version")).join(gone, ["doc_id", "version"], "left").drop("version").na.fill(none)


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    return quality(table(spark, sf_dir, "documents")).select("doc_id", *counts, "base_failed", "kept", "lang", "log_perplexity", "upper", "word_perplexity", "word_lower", "word_upper")


def op9_token_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    counted = count_tokens(table(spark, sf_dir, "documents"), tokenizer_path("piece_bpe_32k.model"))
    return counted.select(F.col("id").alias("doc_id"), "n_bytes", "n_tokens", (F.col("n_tokens") > 4096).alias("over_limit"))


def op10_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return token_digest(write_tokens(docs, tokenizer_path("byte_bpe_50k.json"), end_id=2), docs)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_decontaminate, op2_pack, op3_near_dedup, op4_chat, op5_warc, op6_lm_score, op7_line_dedup, op8_quality, op9_token_count, op10_token_output)}


def _escaped(column: str) -> str:
    """SQL twin of ``escape``: the length is all that is asked, so each control string adds one."""
    out = f"replace({column}, '\\', '\\\\')"
    for c in chat_format.CONTROL:
        out = f"replace({out}, '{c}', '{c[0]}\\{c[1:]}')"
    return out


_ASCII_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLES: dict[str, str] = {
    "op3_near_dedup": f"""
with recursive w as (select doc_id, regexp_extract_all({_ASCII_LOWER}, '[^\\x20\\x09-\\x0D]+') ws from documents),
s as (select distinct doc_id, unnest(case when len(ws) = 0 then [] when len(ws) < 3 then [array_to_string(ws, ' ')]
        else list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) end) g from w),
n as (select doc_id, count(*) k from s group by doc_id),
p as (select a.doc_id a, b.doc_id b, count(*) both_n from s a join s b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
e as (select p.a, p.b from p join n x on x.doc_id = p.a join n y on y.doc_id = p.b where 100 * both_n >= 85 * (x.k + y.k - both_n)),
sym as (select a, b from e union select b, a from e),
r as (select doc_id id, doc_id top from documents union select sym.b, r.top from r join sym on sym.a = r.id),
c as (select id, min(top) top from r group by id)
select d.doc_id, coalesce(n.k, 0)::bigint n_shingles, c.top component_id, d.doc_id = c.top kept
from documents d left join n on n.doc_id = d.doc_id join c on c.id = d.doc_id""",
    "op4_chat": f"""
with t as (select conv_id, turn, coalesce(role, '') role, coalesce(text, '') body from conversations
  union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]')
select conv_id, count(*)::bigint n_turns, sha256(string_agg(role || chr(10) || body || chr(10), '' order by turn, role, body)) turns_sha256,
  coalesce(sum(length(body)) filter (role = 'assistant'), 0)::bigint loss_chars,
  sha256(coalesce(string_agg(body, '' order by turn, role, body) filter (role = 'assistant'), '')) loss_sha256,
  sum(length({_escaped("role")}) + length({_escaped("body")}) + {sum(map(len, chat_format.MARKS))})::bigint formatted_chars
from t group by conv_id""",
    "op5_warc": """
with p as (select page_id, coalesce(html, '') html, sha1(coalesce(html, '')) h from pages),
b as (select h, array_to_string(list_transform(range(0, 32), lambda i:
        substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((('0x' || substr(h, (i // 4 * 5 + 1)::int, 5))::int >> (15 - 5 * (i % 4))::int) & 31)::int, 1)), '') digest
      from (select distinct h from p)),
m as (select h, max(page_id) head from p group by h)
select p.page_id, octet_length(encode(p.html))::bigint payload_bytes, b.digest payload_digest,
  case when p.page_id = m.head then 'response' else 'revisit' end record_type,
  case when p.page_id <> m.head then m.head end refers_to
from p join b using (h) join m using (h)""",
}
