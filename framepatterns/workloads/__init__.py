"""The experiment workloads and one registered query for each operator."""
