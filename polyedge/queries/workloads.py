"""The experiment workloads as queries (rows only: trained models have no SQL)."""

from __future__ import annotations

from functools import partial

from polyedge.plans import workloads as L

QUERIES = {
    "q_accuracy_plant": partial(L.accuracy, preset="plant"),
    "q_accuracy_network": partial(L.accuracy, preset="network"),
    "q_accuracy_telemetry25": partial(L.accuracy, preset="telemetry25"),
    "q_accuracy_telemetry50": partial(L.accuracy, preset="telemetry50"),
    "q_accuracy_testbed38": partial(L.accuracy, preset="testbed"),
    "q_accuracy_given_plant": partial(L.accuracy, preset="plant", carrier=False),
    "q_accuracy_given_network": partial(L.accuracy, preset="network", carrier=False),
    "q_accuracy_given_telemetry25": partial(L.accuracy, preset="telemetry25", carrier=False),
    "q_accuracy_given_telemetry50": partial(L.accuracy, preset="telemetry50", carrier=False),
    "q_accuracy_given_testbed38": partial(L.accuracy, preset="testbed", carrier=False),
    "q_fault_rate20": L.fault_rates,
    "q_leaderboard": partial(L.leaderboard, preset="telemetry25"),
    "q_leaderboard_plant": partial(L.leaderboard, preset="plant"),
    "q_leaderboard_network": partial(L.leaderboard, preset="network"),
    "q_leaderboard_telemetry50": partial(L.leaderboard, preset="telemetry50"),
    "q_leaderboard_testbed38": partial(L.leaderboard, preset="testbed"),
    "q_ablation": partial(L.ablation, preset="telemetry25"),
    "q_ablation_plant": partial(L.ablation, preset="plant"),
    "q_ablation_telemetry50": partial(L.ablation, preset="telemetry50"),
    "q_wk_sweep": L.wk_sweep,
    "q_diagnosis": L.diagnosis,
    "q_forecast_vs_truth": L.forecast_vs_truth,
    "q_case_study": L.case_rows,
    "q_control_search": L.control_search,
}
ORACLES: dict[str, str] = {}
