"""Direct exchange of arrays between the tasks of a barrier stage."""

from __future__ import annotations

import json
import secrets
import threading
from multiprocessing.connection import Client, Listener

import numpy as np


class Peers:
    """Connections between all tasks of the barrier stage that this is created in.

    The stage's own barrier waits a second for each message, so it is used once, to tell each other addresses and a key;
    connections are authenticated by that key. If a task is lost, its connections break, all others fail with it, and the
    stage starts again as a whole, as barrier stages do.
    """

    def __init__(self):
        from pyspark import BarrierTaskContext

        context = BarrierTaskContext.get()
        self.rank = context.partitionId()
        hosts = [t.address.rsplit(":", 1)[0] for t in context.getTaskInfos()]
        self.count = len(hosts)
        self.key = secrets.token_hex(16)
        listeners = {}
        self.links: list = [None] * self.count
        # The key of the listening side is not known before the gather, so the listener is made without one and checks it by hand.
        listeners[self.rank] = listener = Listener((hosts[self.rank], 0), backlog=self.count)
        told = [json.loads(x) for x in context.allGather(json.dumps([listener.address[1], self.key]))]
        for other in range(self.rank):
            link = Client((hosts[other], told[other][0]))
            link.send_bytes(json.dumps([self.rank, told[other][1]]).encode())
            self.links[other] = link
        while any(link is None for k, link in enumerate(self.links) if k > self.rank):
            link = listener.accept()
            other, key = json.loads(link.recv_bytes(256))
            if not secrets.compare_digest(key, self.key):
                link.close()
                continue
            self.links[other] = link
        listener.close()

    def __enter__(self) -> Peers:
        return self

    def __exit__(self, *failure) -> None:
        for link in self.links:
            if link is not None:
                link.close()

    def exchange(self, arrays: list[np.ndarray]) -> list[np.ndarray]:
        """Send an array to each task, and get one of the same kind from each; both in the order of the tasks."""

        def send() -> None:
            for link, x in zip(self.links, arrays):
                if link is not None:
                    link.send_bytes(np.ascontiguousarray(x).tobytes())

        sender = threading.Thread(target=send)
        sender.start()
        got = [arrays[self.rank] if link is None else np.frombuffer(link.recv_bytes(), dtype=arrays[0].dtype) for link in self.links]
        sender.join()
        return got
