"""DuckDB twins of the queries that SQL can express."""

from __future__ import annotations

from .chat import HOSTILE
from .url_filter import RULES


def chat_sql() -> str:
    flags = r"'<\|im_(start|end)\|>|<\\+\|'"
    role = lambda c: f"length({c}) + 5 * (length({c}) - length(replace({c}, chr(10), '')))"  # noqa: E731  a line feed takes six characters
    escape = lambda c: rf"regexp_replace({c}, '<(\\*)\|', '<\1\\|', 'g')"
    return rf"""
with turns as (
  select conv_id::bigint conv_id, turn::bigint turn, coalesce(role, '') "role", coalesce(text, '') "text" from conversations
  union all select -1, 0, 'user', '{HOSTILE}' union all select -1, 1, 'assistant', '{HOSTILE}'
), marked as (select *, regexp_matches("role", {flags}) or regexp_matches("text", {flags}) or contains("role", chr(10)) or contains("role", '<|lf|>') hostile from turns)
select conv_id, count(*)::bigint n_turns,
  sha256(string_agg("role" || chr(10) || "text" || chr(10), '' order by turn nulls first, "role", "text")) turns_sha256,
  coalesce(sum(length("text")) filter (where "role" = 'assistant'), 0)::bigint loss_chars,
  sha256(coalesce(string_agg("text", '' order by turn nulls first, "role", "text") filter (where "role" = 'assistant'), '')) loss_sha256,
  sum(24 + case when hostile then {role(escape('"role"'))} else length("role") end + length(case when hostile then {escape('"text"')} else "text" end))::bigint formatted_chars
from marked group by conv_id"""


def url_sql() -> str:
    host, path = r"coalesce(translate(regexp_extract(url, '(?s)^.*?://([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '')", r"coalesce(regexp_extract(url, '(?s)^.*?://[^/?#]*([^?#]*)', 1), '')"

    def rule(h: str, p: str) -> str:
        tests = []
        for _, r in sorted(RULES, key=lambda r: -len(r[1])):
            rule_host, slash, rest = r.partition("/")
            tests.append(f"when ({h} = '{rule_host}' or ends_with({h}, '.{rule_host}')) and starts_with({p}, '{slash}{rest}') then '{r}'")
        return f"case {' '.join(tests)} end"

    verdict = "case rule " + " ".join(f"when '{r}' then '{v}'" for v, r in RULES) + " end"
    return rf"""
with recursive p as (select page_id, url, html, {host} host, {path} path from pages),
ruled as (select *, {rule("host", "path")} rule from p),
spelt as (
  select url, regexp_replace(regexp_replace(host, '^www\.', ''), ':(80|443)$', '') || regexp_replace(path, '/+$', '')
    || coalesce('?' || nullif(array_to_string(list_sort(list_filter(string_split(regexp_extract(url, '(?s)^[^?#]*\?([^#]*)', 1), '&'), lambda x: x <> '' and not regexp_matches(x, '^(utm_[a-z]+|ref|fbclid|gclid)(=|$)'))), '&'), ''), '') form
  from ruled where host <> ''),
links as (
  select distinct a.url a, b.url b from spelt a join spelt b using (form) where a.url <> b.url
  union select url, regexp_extract(html, '<link[^>]*rel="canonical"[^>]*href="([^"]+)"', 1) from p where html like '%rel="canonical"%'),
edges as (select a, b from links union select b, a from links),
reach(a, b) as (select a, b from edges union select r.a, e.b from reach r join edges e on e.a = r.b),
verdicts as (select distinct url, {verdict} v from (select url, {rule("h", "q")} rule from (select url, {host} h, {path} q from (select a url from edges) s) t) u),
spread as (select r.a url from (select a, b from reach union select a, a from edges) r join verdicts v on v.url = r.b group by r.a having bool_or(coalesce(v.v = 'block', false)) and not bool_or(coalesce(v.v = 'allow', false)))
select page_id, host, path, rule, case when rule is not null then {verdict} when url in (select url from spread) then 'block' else 'allow' end verdict, coalesce(url in (select url from spread), false) alias_blocked
from ruled"""
