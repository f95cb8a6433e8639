"""The operators' queries over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from unscramble.llm.chat import op5_chat_windows
from unscramble.llm.fingerprints import op1_order_minhash
from unscramble.llm.neardup import op3_weighted_minhash
from unscramble.llm.packing import op9_best_fit_packing
from unscramble.llm.personal import op7_personal_data
from unscramble.llm.pieces import op6_piece_transducer
from unscramble.llm.quality import op4_quality
from unscramble.llm.token_counts import op10_token_counts
from unscramble.llm.topk import OP2_SQL, op2_voronoi_top_k
from unscramble.llm.warc import OP8_SQL, op8_warc

QUERIES = {
    "op1_order_minhash": op1_order_minhash,
    "op2_voronoi_top_k": op2_voronoi_top_k,
    "op3_weighted_minhash": op3_weighted_minhash,
    "op4_quality": op4_quality,
    "op5_chat_windows": op5_chat_windows,
    "op6_piece_transducer": op6_piece_transducer,
    "op7_personal_data": op7_personal_data,
    "op8_warc": op8_warc,
    "op9_best_fit_packing": op9_best_fit_packing,
    "op10_token_counts": op10_token_counts,
}

#: The others compute signatures, model scores or tokenizer ids, which SQL has no way to say; tests hold them against
#: brute force, the tokenizers' own libraries and round trips.
SQL = {"op2_voronoi_top_k": OP2_SQL, "op8_warc": OP8_SQL}
