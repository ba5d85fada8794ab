"""Tables, readers, writers, generators and the workloads made from them."""
