"""DuckDB SQL for the training-data queries that SQL can express."""

from __future__ import annotations

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

NEAR_DUPLICATES = rf"""with recursive split as materialized (select doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') as w from documents),
sets as materialized (select doc_id, case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')] else list_distinct([array_to_string(w[i:i + 4], ' ') for i in range(1, len(w) - 3)]) end as s from split),
posts as materialized (select doc_id, len(s) as n, hash(unnest(s)) as h, unnest(s) as x from sets),
shared as materialized (select a.doc_id as a, b.doc_id as b, any_value(a.n) as na, any_value(b.n) as nb, count(*) as hits from posts a join posts b on a.h = b.h and a.x = b.x and a.doc_id < b.doc_id group by 1, 2),
links as materialized (select a, b from shared where 100 * hits >= 75 * (na + nb - hits) union all select b, a from shared where 100 * hits >= 75 * (na + nb - hits)),
reach(root, v) as (select doc_id, doc_id from documents union select root, b from reach join links on a = v),
least as (select root as doc_id, min(v) as component_id from reach group by 1)
select doc_id, len(s)::bigint as n_shingles, component_id, doc_id = component_id as kept from sets join least using (doc_id)"""

SOURCE_MIX = r"""with sized as materialized (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents),
sums as (select source, sum(size)::bigint as source_size from sized group by source),
weighed as (select source, source_size, ([5, 2, 1])[((row_number() over (order by source collate "C" nulls last) - 1) % 3 + 1)::int]::double as weight, (source_size * 2)::double as cap from sums),
ratios as (select *, cap / weight as ratio from weighed),
levels as (select *, (sum(source_size) over ()::double * 1.5 - coalesce(sum(cap) over (order by ratio, source nulls last rows between unbounded preceding and 1 preceding), 0.0)) / sum(weight) over (order by ratio, source nulls last rows between current row and unbounded following) as level from ratios),
targets as (select source, source_size, case when f.level is null or f.level >= ratio then cap else f.level * weight end as target from levels left join (select ratio as r, level from levels where level <= ratio order by ratio, level limit 1) f on true),
units as materialized (select doc_id, source, size, greatest(floor(sqrt((size + 1)::double) * 1024.0), 1)::bigint as tilt from sized),
heaps as (select source, tilt, sum(size)::hugeint as words from units where size > 0 group by 1, 2),
steps as (select h.source, tilt, t.target, coalesce(sum(words) over (partition by h.source order by tilt desc rows between unbounded preceding and 1 preceding), 0)::double as held, (sum(words * tilt) over (partition by h.source order by tilt desc rows between current row and unbounded following))::double as open from heaps h join targets t on h.source is not distinct from t.source),
leveled as (select source, arg_max((target - 2 * held) / open, tilt) as level from steps where (target - 2 * held) / open * tilt < 2 group by source),
dues as (select d.*, t.source_size, t.target, case when t.target >= 2 * t.source_size then 2.0::double else least(coalesce(l.level, 1e300) * tilt, 2.0::double) end as due from units d join targets t on d.source is not distinct from t.source left join leveled l on l.source is not distinct from d.source),
drawn as (select *, floor(due)::bigint as whole, least(greatest(due - floor(due), 1e-9), 1 - 1e-9) as chance, (('0x' || md5('11:' || coalesce(doc_id, -9223372036854775808) || ':' || size)[1:13])::bigint + 0.5::double) / 4503599627370496.0::double as u from dues),
turned as (select *, (u / (1 - u)) / (chance / (1 - chance)) as odds, due > floor(due) as open from drawn),
owed as (select source, max(target) - sum(whole * size) as owed from turned group by source),
ranked as (select t.*, o.owed, coalesce(sum(case when open then size end) over (partition by t.source order by open desc, odds / (1 + odds), doc_id, size rows between unbounded preceding and 1 preceding), 0) as ahead from turned t join owed o on t.source is not distinct from o.source),
cut as (select *, open and not bool_or(open and ahead + size / 2.0 > owed) over (partition by source order by open desc, odds / (1 + odds), doc_id, size rows between unbounded preceding and current row) as taken from ranked)
select doc_id, size, source_size, target, ((whole + case when taken then 1 else 0 end) * size)::bigint as taken from cut"""

ORACLES = {"op1_near_duplicates": NEAR_DUPLICATES, "op2_source_mix": SOURCE_MIX}
