"""Experiment workloads; importing this package registers their queries."""
from entlink.workloads import core  # noqa: F401
from entlink.workloads import surrounding  # noqa: F401
from entlink.workloads import learned  # noqa: F401
from entlink.workloads import experiments  # noqa: F401
