"""Declared schemas of the engine's relations, and the check at its borders."""

from __future__ import annotations

from pyspark.sql import DataFrame


DDL = {
    "variables": "model_id long, var_id long, card int",
    "node_params": "model_id long, var_id long, theta double",
    "edges": "model_id long, src long, dst long, theta double",
    "weighted_edges": "model_id long, src long, dst long, weight double",
    "cliques": "model_id long, clique_id long, members array<long>, theta double",
    "potential_rows": "model_id long, clique_id long, assignment array<int>, phi double",
    "assignment": "model_id long, var_id long, cluster int",
    "cluster_states": "model_id long, cluster int, state long, q double",
    "marginals": "model_id long, var_id long, state int, prob double",
    "evidence": "model_id long, var_id long, state int",
}


def require_schema(df: DataFrame, name: str) -> DataFrame:
    """``df`` with exactly the declared columns, cast to their types; a missing column is an error."""
    wanted = [c.strip().split(" ", 1) for c in DDL[name].split(",")]
    missing = [c for c, _ in wanted if c not in df.columns]
    if missing:
        raise ValueError(f"{name} lacks {', '.join(missing)}")
    return df.select(*[df[c].cast(kind).alias(c) for c, kind in wanted])

