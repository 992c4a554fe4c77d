"""The paradigms and centralized methods that the engine is compared with."""
