"""The experiment workloads and checks behind the queries of the driver contract."""
