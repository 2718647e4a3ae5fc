"""Cost models, planners and experiment workloads."""
