from webgather.plans import content, engine, flow, gather, snapshot, store, web  # noqa: F401
