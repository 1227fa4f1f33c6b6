"""The joint method in SQL, as a table function over batches."""

from __future__ import annotations

from pyspark.sql import SparkSession

from jointsem.functions.expressions import register as register_expressions
from jointsem.models.base import Pool, Records
from jointsem.plans.joint import label_records
from jointsem.plans.params import Params


def register(spark: SparkSession, pool: Pool, params: Params | None = None, name: str = "joint_classify") -> None:
    """SELECT * FROM joint_classify(TABLE(batched) PARTITION BY (batch_id), 'instruction', 'label,label,...').

    The table has columns id, text, batch_id and, for the simulated model, hidden.
    """
    from pyspark.sql.functions import udtf

    params = params or Params()

    @udtf(returnType="id: bigint, pred: string, batch_id: bigint, cluster_id: int")
    class JointClassify:
        def __init__(self) -> None:
            self.rows: list[tuple] = []
            self.asked: tuple[str, list[str]] = ("", [])

        def eval(self, row, instruction: str, labels: str):
            d = row.asDict()
            self.asked = instruction, [x.strip() for x in labels.split(",")]
            self.rows.append((int(d["id"]), d["text"] or "", d.get("hidden"), int(d["batch_id"])))

        def terminate(self):
            if not self.rows:
                return
            self.rows.sort()
            instruction, labels = self.asked
            records = Records([r[0] for r in self.rows], [r[1] for r in self.rows], [r[2] for r in self.rows])
            found = label_records(records, "classify", instruction, labels, len(labels), pool, params, self.rows[0][3])
            for i, p, c in zip(found["id"], found["pred"], found["cluster_id"], strict=True):
                yield int(i), p, self.rows[0][3], int(c)

    spark.udtf.register(name, JointClassify)
    register_expressions(spark)
