"""Tables, streams and the fixed derivations of the experiment workloads."""
