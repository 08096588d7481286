"""Strategy choice and the experiment workloads."""
