"""The fixed row types of the engine, as DDL; `id` stands for the caller's identifier column."""

PHRASE = "phrase_no int, start long, len long, src long, sym long"
EDIT = "step int, op string, x int, y int, sym long"
STEP = "step int, x int, y int, op string"
COST = "oracle_reads long, grover_calls long, grover_queries double, grover_time double, lce_calls long, lz_calls long, comparisons long, q_tokens double, t_tokens double, restarts long, paused long, resumed long, killed long, q_useful double, q_own double, q_terminated double, t_useful double, t_own double, t_terminated double"
SUFFIX = "pos long, rank long, lcp long, bwt long, lf long"
RUN = "run_no long, sym long, row_start long, row_end long, lf_start long"
INTERVAL = "s long, e long, img_s long, img_e long, sym long"
RULE = "nt long, left long, right long, len long, depth int, sym long"
EVENT = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
DOCUMENT = "doc_id long, text string, lang string, source string, n_chars long"
BLOCK = "text_id long, block_no long, start long, syms array<int>"
