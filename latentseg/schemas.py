"""Result types, as DDL strings so that workers can import them. Only vocabularies and label sets are data-driven; adding a label adds rows, never columns."""

VOCAB = "token_id int, token string, token_len int, is_base boolean"
EDGE = "struct<s:int,e:int,t:int>"
LATTICE = f"label string, chunk string, n long, edges array<{EDGE}>"
THETA = "label string, token_id int, logp double, logp_fx long, seen boolean"
LABEL_STATS = "label string, n_samples long, n_tokens double, floor double, entropy double, rounds int, tv double"
TOP = "array<struct<label:string,score:double>>"
