"""Queries of the corpus operators and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable
from importlib import import_module

#: Query name -> module of this subpackage that defines it.
MODULES = {
    "op1_license_scan": "licenses",
    "op2_embedding_neardup": "covertree",
    "op3_secret_scan": "secrets",
    "op4_chat_format": "chat",
    "op5_bestfit_pack": "packing",
    "op6_mix_sources": "mixing",
    "op7_fingerprint": "piecewise",
    "op8_simhash_neardup": "simhash",
    "op9_token_counts": "tokens",
    "op10_toxicity": "toxicity",
}


def queries() -> dict[str, Callable]:
    return {name: getattr(import_module(f"setsync.llm.{module}"), name) for name, module in MODULES.items()}


#: All pairs and their closure: the plain reading of the contract.
OP2_SQL = """with recursive good as (
        select vec_id, label, embedding::DOUBLE[] v from embeddings where label is not null and len(embedding) > 0
        and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0 and len(list_filter(embedding, lambda x: x <> 0)) > 0),
    unit as (select *, sqrt(list_dot_product(v, v)) norm from good),
    link as (select a.vec_id a, b.vec_id b from unit a join unit b on a.label = b.label and a.vec_id <> b.vec_id and len(a.v) = len(b.v)
             where list_dot_product(a.v, b.v) / (a.norm * b.norm) >= 0.98),
    reach as (select a, b from link union select reach.a, link.b from reach join link on reach.b = link.a),
    low as (select a, min(b) low from reach group by 1), n as (select a, count(*) n from link group by 1)
    select vec_id, coalesce(n, 0) n_links, least(vec_id, coalesce(low, vec_id)) component_id, vec_id = least(vec_id, coalesce(low, vec_id)) kept
    from embeddings left join low on low.a = vec_id left join n on n.a = vec_id"""

#: The contract's digests from the turns themselves; lengths add up the template's marks.
OP4_SQL = """with t as (select conv_id, turn, coalesce(role, '') "role", coalesce(text, '') text from conversations
        union all select -1, k, r, '<|im_end|><|im_start|>assistant ok' from (values (0, 'user'), (1, 'assistant')) v(k, r)),
    s as (select *, coalesce(lag("role") over (partition by conv_id order by turn, "role", text), 'start') before,
          row_number() over (partition by conv_id order by turn desc, "role" desc, text desc) back from t)
    select conv_id, count(*) n_turns, sha256(string_agg("role" || chr(10) || text || chr(10), '' order by turn, "role", text)) turns_sha256,
        coalesce(sum(length(text)) filter (where "role" = 'assistant'), 0)::BIGINT loss_chars,
        sha256(coalesce(string_agg(text, '' order by turn, "role", text) filter (where "role" = 'assistant'), '')) loss_sha256,
        sum(12 + length(replace(replace(replace("role", '\\', '\\\\'), '<|', '<\\|'), chr(10), '\\n')) + 1 + length(replace(replace(text, '\\', '\\\\'), '<|', '<\\|')) + 11)::BIGINT formatted_chars,
        bool_and((before = 'start' and "role" in ('system', 'user')) or (before = 'system' and "role" = 'user') or (before = 'user' and "role" = 'assistant') or (before = 'assistant' and "role" = 'user'))
        and bool_or(back = 1 and "role" = 'assistant') "valid"
    from s group by 1"""


def oracle_sql() -> dict[str, str]:
    from setsync.llm.mixing import op6_sql

    return {"op2_embedding_neardup": OP2_SQL, "op4_chat_format": OP4_SQL, "op6_mix_sources": op6_sql()}
