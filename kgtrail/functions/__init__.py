"""Column functions composed of built-ins; nothing here leaves the JVM."""
