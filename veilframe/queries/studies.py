"""Queries of the experiments."""

from __future__ import annotations

from ..plans import bench, workloads

QUERIES = {
    "study_accuracy": lambda spark, d: workloads.accuracy_study(spark, d, ("doc_letters", "cust_spend"), ("nb",)),
    "study_resistance": lambda spark, d: workloads.resistance_study(spark, d, ("cust_spend", "part_profile"), ("ni", "io")),
    "study_resistance_ranks": lambda spark, d: workloads.resistance_ranks(workloads.resistance_study(spark, d, ("cust_spend", "part_profile"), ("ni", "io"))),
    "study_guarantee_dynamics": workloads.guarantee_dynamics,
    "study_sigma_sweep": lambda spark, d: workloads.sigma_sweep(spark, d, "part_profile"),
    "study_selection": workloads.selection_ablation,
    "study_steps": workloads.step_ablation,
    "study_entropy": workloads.entropy_study,
    "study_tuple_ks": workloads.tuple_ks_study,
    "study_attribute_ks": workloads.attribute_ks_study,
    "study_phi_curves": workloads.phi_curves,
    "study_time": lambda spark, d: spark.createDataFrame(bench.time_sweep(spark, d, "li9", (0.5, 1.0), (3, 6), ("SMP-cov", "SMP-scan")), "method string, rows long, attributes int, seconds double"),
}
ORACLES: dict[str, str] = {}
