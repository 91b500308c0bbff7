"""Registered queries, their SQL twins, and the experiment workloads."""


def load() -> tuple[dict, dict]:
    """(plans, SQL) of all registered queries."""
    from patchspace.plans import baselineplans, core, experiments, frames, rasterplans, sqlplans, streamplans  # noqa: F401
    from patchspace.plans.registry import PLANS, SQL

    return PLANS, SQL
