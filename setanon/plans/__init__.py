"""End-to-end plans, experiment workloads and the registry of named queries."""
