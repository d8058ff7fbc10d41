"""DuckDB SQL for the queries that SQL can express."""

ORACLES: dict[str, str] = {
    "op2_warc": """
with p as (
    select page_id, coalesce(html, '') as html, strlen(coalesce(html, '')) as n, sha256(coalesce(html, '')) as digest from pages
), g as (
    select *, min(page_id) over (partition by digest) as first from p
)
select page_id, n::bigint as payload_bytes, digest as payload_digest,
    case when n >= 100 and page_id is distinct from first and first is not null then 'revisit' else 'response' end as record_type,
    case when n >= 100 and page_id is distinct from first then first end as refers_to
from g""",
}
