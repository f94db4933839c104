"""The queries of this package and the SQL that some of them equal."""

from aclvec.llm import jaccard, linededup, mixing
from aclvec.llm.bpe import op6_bpe_codec
from aclvec.llm.hmm import op5_hmm_scores
from aclvec.llm.jaccard import op10_jaccard_join
from aclvec.llm.langid import op1_language_id
from aclvec.llm.linecrf import op4_line_rules
from aclvec.llm.linededup import op8_line_dedup
from aclvec.llm.media import op2_media
from aclvec.llm.mixing import op9_mixing
from aclvec.llm.quality import op3_quality
from aclvec.llm.urlfilter import op7_url_filter

OPERATORS = (
    op1_language_id, op2_media, op3_quality, op4_line_rules, op5_hmm_scores,
    op6_bpe_codec, op7_url_filter, op8_line_dedup, op9_mixing, op10_jaccard_join,
)
QUERIES = {f.__name__: f for f in OPERATORS}
ORACLES: dict[str, str] = {"op8_line_dedup": linededup.ORACLE, "op9_mixing": mixing.oracle(), "op10_jaccard_join": jaccard.ORACLE}
