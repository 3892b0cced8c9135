"""DuckDB SQL for the contract queries that SQL can express."""

from __future__ import annotations

from .chat import CLOSE, OPEN, SPLIT
from .secrets import ACCESS, ASSIGN, ENDPOINT, HEX, IDENTIFIER, SCOPE, WEAK_SECRET

_WORDS = r"regexp_extract_all(translate(coalesce(text,''),'ABCDEFGHIJKLMNOPQRSTUVWXYZ','abcdefghijklmnopqrstuvwxyz'),'[^\x20\x09-\x0D]+')"


def _shingles(table: str, ident: str, k: int) -> str:
    return f"(select distinct {ident}, unnest(case when len(w)>={k} then list_transform(range(1,len(w)-{k - 2}), lambda i: array_to_string(w[i:i+{k - 1}],' ')) when len(w)>0 then [array_to_string(w,' ')] else [] end) s from (select {ident}, {_WORDS} w from {table}))"


JACCARD = f"""with recursive sh as {_shingles("documents", "doc_id", 4)}, n as (select doc_id, count(*) n from sh group by all),
 ov as (select a.doc_id x, b.doc_id y, count(*) c from sh a join sh b on a.s=b.s and a.doc_id<b.doc_id group by all),
 ln as (select x, y from ov join n a on a.doc_id=x join n b on b.doc_id=y where 100*c>=85*(a.n+b.n-c)), e as (select x, y from ln union all select y, x from ln),
 rc as (select x doc_id, x r from e union select rc.doc_id, e.y from rc join e on e.x=rc.r), comp as (select doc_id, min(r) r from rc group by all)
select d.doc_id, coalesce(n,0)::bigint n_shingles, coalesce(r,d.doc_id) component_id from documents d left join n on n.doc_id=d.doc_id left join comp on comp.doc_id=d.doc_id"""

CONTAINED = f"""with ds as {_shingles("documents", "doc_id", 5)}, bs as {_shingles("benchmark", "item_id", 5)}, bn as (select item_id, count(*) n from bs group by all),
 ov as (select doc_id, item_id, count(*) c from ds join bs using (s) group by all)
select doc_id, item_id, n item_shingles, c shared, c/n containment from ov join bn using (item_id) where 100*c>=80*n"""


def _spans(name: str, pattern: str, kind: str, rank: int, group: int = 0, least: int = 0) -> str:
    q = pattern.replace("'", "''")
    return f"""{name} as (select doc_id, '{kind}' kind, {rank} rank, s, s+length(m) e from (select doc_id, unnest(ms) m, unnest(ks) k, unnest(list_transform(range(1,len(ms)+1), lambda i: list_sum(list_transform(gs[1:i], lambda x: length(x)))+coalesce(list_sum(list_transform(ms[1:i-1], lambda x: length(x))),0))) s
 from (select doc_id, string_split_regex(t,'{q}') gs, regexp_extract_all(t,'{q}') ms, regexp_extract_all(t,'{q}',{group}) ks from t)) where length(k)>={least})"""


def _near(a: str, b: str) -> str:
    return f"exists (select 1 from {b} o where o.doc_id={a}.doc_id and o.s<={a}.e+{SCOPE} and {a}.s<=o.e+{SCOPE} and (o.e<={a}.s or {a}.e<=o.s))"


SECRETS = f"""with t as (select doc_id, coalesce(text,'') t from documents), {_spans("a", ASSIGN, "assign", 0, 2, 8)}, {_spans("k", ACCESS, "access", 1, 0, 16)}, {_spans("h", HEX, "hex", 2)},
 {_spans("w", WEAK_SECRET, "linked_secret", 4)}, {_spans("i", IDENTIFIER, "linked_id", 3)}, {_spans("p", ENDPOINT, "linked_endpoint", 5)},
 sec as (select * from w union all select * from a union all select * from h), other as (select * from i union all select * from p),
 base as (select * from a union all select * from k union all select * from h),
 every as (select * from base union all select * from i where {_near("i", "sec")} union all select * from w where {_near("w", "other")} union all select * from p where {_near("p", "sec")} and {_near("p", "i")}),
 bj as (select doc_id, string_agg(kind||':'||s||':'||e, ',' order by s, rank, e) j, count(*) filter (where kind='assign') na, count(*) filter (where kind='access') nk, count(*) filter (where kind='hex') nh from base group by all),
 ej as (select doc_id, string_agg(kind||':'||s||':'||e, ',' order by s, rank, e) j from every group by all)
select t.doc_id, coalesce(na,0)::bigint n_assign, coalesce(nk,0)::bigint n_access, coalesce(nh,0)::bigint n_hex, sha256(coalesce(bj.j,'')) base_sha256, coalesce(ej.j,'') spans from t left join bj on bj.doc_id=t.doc_id left join ej on ej.doc_id=t.doc_id"""

_ESC = r"length(replace(replace({c},'\','\s'),'<|','\l|'))"
CHAT = rf"""with c as (select conv_id::bigint conv_id, turn::bigint turn, coalesce(role,'') role, coalesce(text,'') body from conversations union all select -7, 0, 'user', '\### Assistant: </turn> ok' union all select -7, 1, 'assistant', '\### Assistant: </turn> ok'),
 f as (select *, {len(OPEN) + len(SPLIT) + len(CLOSE)}+{_ESC.format(c="role")}+{_ESC.format(c="body")} n, row_number() over (partition by conv_id order by turn desc, role desc, body desc)=1 last_turn from c),
 g as (select *, sum(n) over (partition by conv_id order by turn, role, body rows unbounded preceding) upto from f)
select conv_id, count(*) n_turns, sha256(string_agg(role||chr(10)||body||chr(10), '' order by turn, role, body)) turns_sha256, coalesce(sum(length(body)) filter (where role='assistant'),0)::bigint loss_chars,
 sha256(coalesce(string_agg(body, '' order by turn, role, body) filter (where role='assistant'),'')) loss_sha256, sum(upto) filter (where role='assistant' or last_turn)::bigint formatted_chars, count(*) filter (where role='assistant' or last_turn) n_examples from g group by conv_id"""

ORACLE_SQL = {"op1_ngram_jaccard_join": JACCARD, "op6_secret_scans": SECRETS, "op7_decontamination": CONTAINED, "op8_chat_formatting": CHAT}
