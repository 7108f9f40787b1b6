"""Row shapes shared by the operators."""

SET_ELEMS = "set_id BIGINT, elem BIGINT"  # distinct rows
FULL_SIG = "set_id BIGINT, f BIGINT, z ARRAY<BIGINT>"  # k full-width minima, mergeable by element-wise min
PAIR_EXACT = "id_l BIGINT, id_r BIGINT, f_l BIGINT, f_r BIGINT, a BIGINT, r DOUBLE"
PAIR_EST = "id_l BIGINT, id_r BIGINT, k INT, b INT, matches BIGINT, e_hat DOUBLE, r_hat DOUBLE"
PR_POINT = "estimator STRING, b INT, k INT, r0 DOUBLE, n_rel BIGINT, n_ret BIGINT, n_hit BIGINT, precision DOUBLE, recall DOUBLE"
MSE_POINT = "pair STRING, estimator STRING, b INT, k INT, reps BIGINT, bias DOUBLE, variance DOUBLE, mse DOUBLE, theory DOUBLE"
SIG_META = "sig_name STRING, family STRING, k INT, b_max INT, domain_size DOUBLE, seed BIGINT, w INT"
