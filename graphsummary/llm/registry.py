"""The registered queries of the text operators and the SQL of those that SQL can express."""

from graphsummary.llm.decontaminate import op2_decontaminate
from graphsummary.llm.exact_dedup import OP4_SQL, op4_exact_dedup
from graphsummary.llm.language_id import op10_language_id
from graphsummary.llm.line_dedup import OP9_SQL, op9_line_dedup
from graphsummary.llm.lm_score import op7_lm_score
from graphsummary.llm.mixing import op3_mixing
from graphsummary.llm.near_dedup import op5_near_dedup
from graphsummary.llm.secrets import op8_secrets
from graphsummary.llm.token_counts import op6_token_counts
from graphsummary.llm.url_filter import OP1_SQL, op1_url_filter

QUERIES = {
    f.__name__: f
    for f in (op1_url_filter, op2_decontaminate, op3_mixing, op4_exact_dedup, op5_near_dedup, op6_token_counts, op7_lm_score, op8_secrets, op9_line_dedup, op10_language_id)
}
ORACLES = {"op1_url_filter": OP1_SQL, "op4_exact_dedup": OP4_SQL, "op9_line_dedup": OP9_SQL}
