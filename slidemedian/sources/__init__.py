"""Tables, sinks and generated inputs."""
