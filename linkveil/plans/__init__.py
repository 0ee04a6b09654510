"""Plans made of operators: the layered protocol and the experiment workloads."""
