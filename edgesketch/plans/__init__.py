"""Cost and accuracy measures and the experiment workloads."""
