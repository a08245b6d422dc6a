"""Cost measures, the choice of a method, experiment workloads, and oracles."""
