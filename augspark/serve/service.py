"""A request from start to end: cached plans, search, the plan's rows, model search in the time left, and the response.

The search keeps back what the cost model expects the model search to take on the plan found so far. Where a final
service can't be predicted, the search has a fixed allowance instead and the service runs as long as it does.
"""

from __future__ import annotations

import time
from dataclasses import replace

from augspark.catalog import Corpus
from augspark.cluster import materialize
from augspark.modelsearch.search import HostedSimulator, ModelSearch
from augspark.search import materialize as rows_of
from augspark.search.cache import PlanCache
from augspark.search.cost import CostModel, budget_split
from augspark.search.engine import Search
from augspark.search.request import Request
from augspark.serve.response import Response, build
from augspark.serve.scorer import ModelScorer, of_plan


class Service:
    """final: broad, trees or hosted, the model search of requests for any model. Other options are those of Search."""

    def __init__(self, corpus: Corpus, cache: PlanCache | None = None, cost: CostModel | None = None, final: str = "broad", policy: str = "cost", fixed_search_s: float = 300.0, task: str = "regression", **search) -> None:
        self.corpus, self.cache, self.cost, self.final, self.policy, self.fixed_search_s, self.task = corpus, cache, cost, final, policy, fixed_search_s, task
        self.search = Search(corpus, cost=cost, **search)

    def answer(self, req: Request) -> Response:
        began = time.monotonic()
        allowed, _ = budget_split(req.budget_s, self.policy if req.model == "any" else "cost", self.fixed_search_s)
        answer, _ = self.search.search(replace(req, budget_s=allowed), cache=self.cache)
        if req.model == "linear":
            return build(req, answer, self.corpus, of_plan(self.search, answer))
        return self.finish(req, answer, began)

    def finish(self, req: Request, answer, began: float) -> Response:
        """The model search on the plan's rows, in the time that is left."""
        wanted = [*req.features, req.target, *req.keys]
        train = req.train if req.validation is None else req.train.select(*wanted).unionByName(req.validation.select(*wanted))
        whole = rows_of.apply(answer.plan, train.select(*wanted), self.corpus, answer.keys)
        table = materialize(whole.select(*[f"`{c}`" for c in (*answer.feature_names, req.target)]), "augmented")
        left = max(0.0, 0.9 * (req.budget_s - (time.monotonic() - began)))  # blending comes after
        search = HostedSimulator(task=self.task) if self.final == "hosted" else ModelSearch(self.final, left, self.task)
        found = search.run(table, answer.feature_names, req.target)
        out = build(req, answer, self.corpus, ModelScorer(self.corpus, answer, found.model), found.model)
        out.model_s, out.score = found.seconds, found.score
        return out
