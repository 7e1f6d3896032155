"""Tables, point builders for the experiment workloads, generators, readers and sinks."""
