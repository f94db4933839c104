"""SQL functions and table functions of the engine."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register(spark: SparkSession) -> None:
    """acl_recall, acl_ef, acl_cost and vec_l2sq as SQL functions (inlined by the optimiser); policy_generate as a table function."""
    defs = {
        "acl_recall(ef DOUBLE, s DOUBLE, k DOUBLE, beta DOUBLE, gamma DOUBLE)": "RETURN least(greatest(CASE WHEN ef * s / k <= gamma THEN ef * s / k ELSE 1 / (1 + exp(-beta * (ef * s / k - gamma))) + gamma - 0.5D END, 0D), 1D)",
        "acl_ef(eps DOUBLE, s DOUBLE, k DOUBLE, beta DOUBLE, gamma DOUBLE)": "RETURN k / s * CASE WHEN eps <= gamma THEN eps ELSE gamma + ln((eps - gamma + 0.5D) / (0.5D - eps + gamma)) / beta END",
        "acl_cost(size DOUBLE, ef DOUBLE, a DOUBLE, b DOUBLE)": "RETURN ln(greatest(size, 2D)) * (a * ef + b)",
        "vec_l2sq(a ARRAY<FLOAT>, b ARRAY<FLOAT>)": "RETURN aggregate(zip_with(a, b, (x, y) -> (CAST(x AS DOUBLE) - y) * (CAST(x AS DOUBLE) - y)), 0D, (acc, x) -> acc + x)",
    }
    for name, body in defs.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name} RETURNS DOUBLE {body}")

    @udtf(returnType="role_id int, doc_id bigint")
    class PolicyGenerate:
        """Roles that draw documents by the portable hash: one call is one task's work."""

        def eval(self, n_roles: int, n_docs: int, m_p: int):
            from aclvec.functions.portable import draw_py

            for r in range(n_roles):
                m = 1 + draw_py(r, 3, m_p)
                for d in sorted({draw_py(r * 1000003 + i, 4, 1 << 20) % n_docs for i in range(1, m + 1)}):
                    yield r, d

    spark.udtf.register("policy_generate", PolicyGenerate)
